"""Surrogates held against plain expectations."""

import random
import re

import pytest
from pyspark.sql import functions as F

from placeminer.llm import surrogates


def rewritten(spark, texts, **options):
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    return [r["text"] for r in surrogates.replaced(df, **options).orderBy("doc_id").collect()]


def test_a_thousand_persons_stay_a_thousand(spark):
    letters = "abdefghiklmnoprstuvz"
    names = [f"{letters[i % 20]}{letters[i // 20 % 20]}{letters[i // 400]}o".capitalize() for i in range(1000)]
    out = rewritten(spark, [f"Mr. {n} Smith" for n in names])
    assert len(set(out)) == 1000 and len({x.split()[2] for x in out}) == 1
    assert not any(x.split()[1] == n for x, n in zip(out, names))
    family = rewritten(spark, [f"Mrs {n}" for n in names])
    assert len(set(family)) == 1000


def test_titles_and_their_lack_do_not_matter(spark):
    out = rewritten(spark, ["Dr. Jane Roe said so.", "Mrs. Jane Roe was there, but Roe, or Jane, or Jane Roe left.", "Prof Sam Roe", "Mr. Robin Hay and Miss Robin Lee", "Jane Roe is only known elsewhere.", "Dr. JANE ROE"])
    a = re.fullmatch(r"Dr\. (\S+) (\S+) said so\.", out[0]).groups()
    b = re.fullmatch(r"Mrs\. (\S+) (\S+) was there, but (\S+), or (\S+), or (\S+) (\S+) left\.", out[1]).groups()
    assert b == (*a, a[1], a[0], *a) and a[0] in surrogates.GIVEN["latin"]["f"]
    assert out[2].split()[2] == a[1] and out[2].split()[1] in surrogates.GIVEN["latin"]["n"]
    x, y = re.fullmatch(r"Mr\. (\S+) \S+ and Miss (\S+) \S+", out[3]).groups()
    assert x == y and x in surrogates.GIVEN["latin"]["n"]
    assert out[4] == "Jane Roe is only known elsewhere." and out[5] == f"Dr. {a[0].upper()} {a[1].upper()}"


def test_scripts_are_kept_or_left(spark):
    out = rewritten(spark, ["Κύριος Νίκος Παπαδόπουλος", "Mrs Ελένη Παπά", "Господин Иван Петров", "Mr. Արամ Սարյան"])
    assert re.fullmatch(r"Κύριος [Ͱ-Ͽ]+ [Ͱ-Ͽ]+", out[0]) and "Νίκος" not in out[0].split()[1:2] or out[0].split()[1] != "Νίκος"
    assert re.fullmatch(r"Mrs [Ͱ-Ͽ]+ [Ͱ-Ͽ]+", out[1]) and out[1].split()[1] in surrogates.GIVEN["greek"]["f"]
    assert re.fullmatch(r"Господин [Ѐ-ӿ]+ [Ѐ-ӿ]+", out[2]) and out[3].startswith("Mr. Ա")


def test_no_length_lets_anything_through(spark):
    secret, local, name = "k9" * 4000, "ab.cd" * 100, "J" + "o" * 300
    out = rewritten(spark, [f'token="{secret}" end', f"to {local}@mail.example.net now", f"Mr. {name} Xu", "mail a@" + ".".join(["b"] * 5000), " Mr. Al Bo, Bo; 10.1.2.3 "])
    assert len(out[0]) == len(secret) + 12 and "k9k9" not in out[0] and local not in out[1] and out[1].endswith(" now")
    assert name not in out[2] and "b.b" not in out[3]
    assert re.fullmatch(" Mr\\. (\\S+) (\\S+), \\2; 2[45]\\d\\.\\d+\\.\\d+\\.\\d+ ", out[4]) and "Bo," not in out[4]


def test_short_numbers_stay_distinct_even_where_their_space_is_full(spark):
    every = [f"+49 {i:03d}" for i in range(1000)] + [f"+49 {i:02d} 1{i:02d}" for i in range(100)]
    out = rewritten(spark, every)
    assert len(set(out[:1000])) == 1000 and len(set(out[1000:])) == 100
    assert all(x != y and re.fullmatch(r"\+49 [\d ]+", y) and len(x) == len(y) for x, y in zip(every, out))


def test_symbols_alone_are_still_replaced(spark):
    out = rewritten(spark, [f'password="{x * 8}"' for x in "!.#*"])
    assert len(set(out)) == 4 and not any(x * 8 in o for x, o in zip("!.#*", out))


def test_texts_are_rewritten_piece_by_piece(spark):
    """A plain version: every entity is looked up among the surrogates of texts that hold it alone."""
    rng = random.Random(5)
    entities = [f"user{i}@mail{i % 3}.org" for i in range(15)] + [f"10.0.{i}.{i + 7}" for i in range(15)] + [f"+1 415 555 {1000 + 7 * i}" for i in range(15)] + [f"{100 + i}-45-{6789 + i}" for i in range(10)]
    entities += [f"Mr. {g} {f}" for g in ("Abe", "Bob", "Cid") for f in ("Stone", "Reed")] + ["4111 1111 1111 1111", "5500-0000-0000-0004"]
    fill = ["plain words", "x = 12 + 3", "1.2.3", "a@b", "line\nbreak", "Ωμέγα", "", "(", "é'è"]
    mixed = [[(fill + entities)[rng.randrange(len(fill) + len(entities))] for _ in range(rng.randrange(12))] for _ in range(150)]
    texts = entities + ["; ".join(m) for m in mixed]
    out = rewritten(spark, texts)
    known = dict(zip(entities, out))
    assert len(set(known.values())) == len(entities) and not set(known.values()) & set(entities)
    for m, o in zip(mixed, out[len(entities):]):
        assert o == "; ".join(known.get(x, x) for x in m)


def test_an_exhausted_space_is_an_error(spark, monkeypatch):
    df = spark.createDataFrame([(i, f"10.0.0.{i}") for i in range(5)], "doc_id long, text string")
    monkeypatch.setattr(surrogates, "stream", lambda key, kind, canon, attempt: F.lit("1" * 128))
    with pytest.raises(RuntimeError):
        surrogates.redrawn(surrogates.entities(df), attempts=2)


def test_columns_of_the_table_do_not_clash(spark):
    df = spark.createDataFrame([("x", "at 10.0.0.1", 7, "c")], "kind string, text string, n_entities long, canon string")
    row = surrogates.replaced(df).first()
    assert row["kind"] == "x" and row["canon"] == "c" and row["n_entities"] == 1 and "10.0.0.1" not in row["text"]
