"""Language bitmasks held against exact sets."""

import numpy as np

from placeminer.llm import langid


def alphabets(n):
    """Texts of ``n`` made-up languages, each with letters of its own beside some that all share."""
    rng = np.random.Generator(np.random.PCG64(3))
    out = []
    for i in range(n):
        letters = [chr(0x4E00 + 40 * i + k) for k in range(12)] + list("aeiou")
        out += [(f"l{i:03d}", " ".join("".join(rng.choice(letters, 4)) for _ in range(30))) for _ in range(6)]
    return out


def test_eighty_languages_are_told_apart(spark):
    rows = [(k, t, x) for k, (x, t) in enumerate(alphabets(80))]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = langid.fit(df.where("doc_id % 6 < 4"))
    assert len(model.languages) == 80 and [w.dtype for w in model.table] == [np.uint64, np.uint16]
    got = {r["doc_id"]: r["lang_pred"] for r in langid.predict(df, model).collect()}
    assert all(got[k] == x for k, _, x in rows)


def test_popcounts_are_those_of_exact_sets_but_for_false_positives(spark, sf01):
    """A plain version with one set of cells a language: no n-gram is forgotten, and corrected counts are near the exact ones."""
    docs = spark.read.parquet(f"{sf01}/documents.parquet")
    seen = docs.where(~langid.held_out(4, 2) & docs["lang"].isNotNull() & docs["text"].isNotNull()).select("text", "lang").collect()
    letters = langid.letter_table()
    counts: dict[str, dict[int, int]] = {}
    for text, lang in seen:
        for c in langid.cell(langid.grams(text, letters)).tolist():
            own = counts.setdefault(lang, {})
            own[c] = own.get(c, 0) + 1
    rates = {x: {c: n / sum(own.values()) for c, n in own.items()} for x, own in counts.items()}
    top: dict[int, float] = {}
    for own in rates.values():
        for c, r in own.items():
            top[c] = max(top.get(c, 0), r)
    sets = {x: {c for c, r in own.items() if r >= 0.34 * top[c]} for x, own in rates.items()}
    model = langid.fit(docs.where(~langid.held_out(4, 2)))
    assert model.languages == sorted(sets)
    same = n = 0
    for r in docs.where(langid.held_out(4, 2)).select("text").collect():
        g = langid.grams(r["text"], letters) if r["text"] else ()
        if not len(g):
            assert model.predict(r["text"], letters) == ("und", 0.0)
            continue
        exact = np.array([sum(c in sets[x] for c in langid.cell(g).tolist()) for x in model.languages])
        hits = model.hits(g)
        assert (hits >= exact).all() and (hits - exact <= len(g) * model.false + 6 * np.sqrt(len(g)) + 3).all()
        n += 1
        same += model.predict(r["text"], letters)[0] == model.languages[int(exact.argmax())]
    assert n > 100 and same >= 0.99 * n


def test_repeated_rows_and_clashing_columns(spark):
    df = spark.createDataFrame([(1, "some words", "en", "x", 0.5), (1, "some words", "en", "y", 0.1), (2, "andere worte", "de", "z", 0.2)], "doc_id long, text string, lang string, lang_pred string, score double")
    out = langid.predict(df, langid.fit(df))
    assert out.columns == ["doc_id", "lang_pred", "score"] and sorted(r["lang_pred"] for r in out.collect()) == ["de", "en", "en"]
