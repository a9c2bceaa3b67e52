"""Surrogates for personal data (op 1, native).

Entities are found by one pattern per type; each is replaced by a keyed surrogate of its own type and format:

- ``email``: letters for letters and digits for digits in the local part, under a reserved example domain;
- ``phone``: the country code stays, every other digit changes, separators stay; short numbers go through a keyed
  permutation of their country code and length, so that even a space that is full keeps them distinct;
- ``card``: digits under the same separators, Luhn-valid if and only if the entity was;
- ``ssn``: digits under the same dashes, in the never-issued 9xx range;
- ``ip``: an address of the reserved block 240/4;
- ``secret``: as many hexadecimal digits or letters and digits, in the same case;
- ``person``: names after a title, each part replaced by one of the same script (Latin, Cyrillic, Greek; names of others are
  not taken for names) and gender. Parts of such names that stand in the same text without a title are replaced alike.

A surrogate is a function of the key, the type and the canonical form (case, separators and title
do not matter), so one entity has one surrogate in all documents; parts of names are keyed alone, so
``Mr. John Smith``, ``Dr. John Smith``, ``Mr. Smith`` and a later ``Smith`` stay one person. A given name has the gender that the
corpus's titles before it agree on; where they tell none, or differ, its surrogate is a name of both. The distinct entities
of the corpus, and the distinct given and family names, are then checked: where two share a surrogate, or one is a real entity
of the corpus, all but one are drawn anew from a space that grows with each attempt, until the surrogates are distinct; if they are not
after ``ATTEMPTS`` rounds an error is raised. Only what differs from the first draw is kept as a table; it reaches the texts as a
literal map while it has at most ``LITERAL`` rows, and by a join on text hashes beyond that.

Edge cases: null texts stay null, empty and clean texts are unchanged; very long texts, entities and names are handled whole; repeated
rows get equal results; without entities nothing is drawn; other columns, whatever their names, are kept as they are by
:func:`replaced` and never read. A name has at most five parts; a phone number whose digits all belong to the country code has none to change.
"""

from __future__ import annotations

import json

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import checkpointed

KEY = "surrogate-key-1"
LITERAL = 2000
ATTEMPTS = 64
#: Phone numbers of at most so many digits after the country code are permuted.
SHORT = 6

#: Titles by the gender that they tell.
MALE = ("Mr", "Herr", "Monsieur", "Señor", "Sr", "Sir", "Господин", "Κύριος")
FEMALE = ("Mrs", "Ms", "Miss", "Frau", "Madame", "Mme", "Señora", "Sra", "Lady", "Госпожа", "Κυρία")
NEUTRAL = ("Dr", "Prof", "Mx")
#: Given names by script and gender.
GIVEN = {
    "latin": {"m": ("Adam", "Boris", "Carl", "David", "Emil", "Felix", "Georg", "Hugo", "Ivan", "Jonas", "Karl", "Leo", "Martin", "Noel", "Oscar", "Paul"), "f": ("Ada", "Berta", "Clara", "Diana", "Emma", "Flora", "Greta", "Helena", "Ida", "Julia", "Karin", "Lena", "Maria", "Nora", "Olga", "Petra"), "n": ("Alex", "Chris", "Dana", "Eden", "Jamie", "Kim", "Lou", "Max", "Nico", "Robin", "Sacha", "Sam", "Sky", "Toni", "Val", "Yuri")},
    "cyrillic": {"m": ("Антон", "Борис", "Виктор", "Глеб", "Денис", "Егор", "Иван", "Кирилл", "Лев", "Максим", "Никита", "Олег", "Павел", "Роман", "Семён", "Юрий"), "f": ("Анна", "Вера", "Галина", "Дарья", "Елена", "Жанна", "Зоя", "Ирина", "Кира", "Лидия", "Мария", "Нина", "Ольга", "Раиса", "София", "Юлия"), "n": ("Женя", "Саша", "Валя", "Слава", "Паша", "Шура", "Тоня", "Витя", "Лера", "Миша", "Коля", "Рома", "Ваня", "Лёша", "Стася", "Юра")},
    "greek": {"m": ("Άγγελος", "Βασίλης", "Γιώργος", "Δημήτρης", "Ηλίας", "Θανάσης", "Κώστας", "Λευτέρης", "Μιχάλης", "Νίκος", "Πέτρος", "Σπύρος", "Στέλιος", "Τάσος", "Φώτης", "Χρήστος"), "f": ("Άννα", "Βάσω", "Γεωργία", "Δήμητρα", "Ελένη", "Ζωή", "Ιωάννα", "Κατερίνα", "Λίνα", "Μαρία", "Νίκη", "Ξένια", "Ρένα", "Σοφία", "Φωτεινή", "Χριστίνα"), "n": ("Άλεξ", "Άρι", "Ντάνι", "Έντι", "Κιμ", "Λου", "Μαξ", "Νόε", "Ρόμπιν", "Σαμ", "Σάσα", "Σκάι", "Τζο", "Τζέιμι", "Τόνι", "Φράνσις")},
}
#: Country codes of telephone numbers.
COUNTRY = r"^(?:1|7|2[07]|3[0-469]|4[013-9]|5[1-8]|6[0-6]|8[1246]|9[0-58]|\d{3})"
#: Syllables of made-up family names, by script.
SYLLABLES = {"latin": ("ba", "del", "fin", "gor", "hal", "jen", "kas", "lum", "mor", "nel", "pad", "quin", "ros", "sten", "tal", "ver"), "cyrillic": ("ба", "дел", "фин", "гор", "хал", "жен", "кас", "лум", "мор", "нел", "пад", "вин", "рос", "стен", "тал", "вер"), "greek": ("βα", "δελ", "φιν", "γορ", "χαλ", "ζεν", "κασ", "λουμ", "μορ", "νελ", "παδ", "κιν", "ροσ", "στεν", "ταλ", "βερ")}
TYPES = ("email", "secret", "ip", "ssn", "card", "phone", "person")

_TITLE = "|".join(sorted((*MALE, *FEMALE, *NEUTRAL), key=len, reverse=True))
_LETTER = r"\p{IsLatin}\p{IsCyrillic}\p{IsGreek}"
_PART = rf"(?=\p{{Lu}})[{_LETTER}][{_LETTER}'-]++(?!\p{{L}})"
#: The patterns, in order of preference where they start at one place. Repetitions are possessive or bounded, so that no text is tried twice.
PATTERNS = {
    "email": r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "secret": r"(?<=[\"'])(?<=(?i:\b(?:token|secret|password|passwd|api[_-]?key|access[_-]?key|auth)[\"']?\s{0,3}[=:]\s{0,3}[\"']))[^\"'\s]{8,}+(?=[\"'])|\b[0-9a-f]{40}\b|\bAKIA[0-9A-Z]{16}\b|\bgh[pousr]_[A-Za-z0-9]{36}\b",
    "ip": r"(?<![\d.])(?:(?:25[0-5]|2[0-4]\d|1?\d?\d)\.){3}(?:25[0-5]|2[0-4]\d|1?\d?\d)(?!\.?\d)",
    "ssn": r"(?<![\d-])\d{3}-\d{2}-\d{4}(?![\d-])",
    "card": r"(?<![\d-])\d{4}([ -]?)\d{4}\1\d{4}\1\d{1,7}(?![\d-])|(?<!\d)3[47]\d{2} \d{6} \d{5}(?!\d)",
    "phone": r"(?<![\d\w])\+\d{1,3}[ .-]?(?:\(\d{1,4}\)|\d{1,4})(?:[ .-]?\d{2,4}){1,4}(?!\d)|(?<![\d\w])\(\d{3}\) ?\d{3}[ .-]\d{4}(?!\d)|(?<![\d\w.-])\d{3}[.-]\d{3}[.-]\d{4}(?![\d-])",
    "person": rf"(?<!\p{{L}})(?:{_TITLE})\.?[ ]{_PART}(?:[ ]{_PART}){{0,4}}+",
}


def _combined() -> str:
    """One pattern; the only group that is referred back to keeps number 1."""
    rest = [PATTERNS[t] for t in TYPES if t != "card"]
    return "|".join([PATTERNS["card"], *rest])


PATTERN = _combined()
#: What every text with an entity holds; cheap, and most texts lack it.
GATE = r"[0-9@\"']|[" + "".join(sorted({t[0] for t in (*MALE, *FEMALE, *NEUTRAL)})) + r"](?:" + "|".join(sorted({t[1:] for t in (*MALE, *FEMALE, *NEUTRAL)})) + r")[. ]"


def is_person(e: Column) -> Column:
    return e.rlike(rf"^(?:{_TITLE})\.?[ ]\p{{Lu}}")


def kind_of(e: Column) -> Column:
    """The type of an entity that the combined pattern found."""
    out = F.lit("phone")
    for t in reversed(("email", "ip", "ssn", "card", "person", "secret")):
        test = {
            "email": e.contains("@") & e.rlike(rf"^(?:{PATTERNS['email']})$"),
            "secret": ~e.contains(" ") & (F.length(e) >= 8) & ~e.rlike(rf"^(?:{PATTERNS['phone']})$"),
            "ip": e.rlike(r"^[\d]{1,3}(\.\d{1,3}){3}$"),
            "ssn": e.rlike(r"^\d{3}-\d{2}-\d{4}$"),
            "card": e.rlike(r"^\d[\d -]*$") & (F.length(F.regexp_replace(e, r"\D", "")) >= 13),
            "person": is_person(e),
        }[t]
        out = F.when(test, F.lit(t)).otherwise(out)
    return out


def canonical(kind: Column, e: Column) -> Column:
    """The form that all mentions of an entity share."""
    return (
        F.when(kind == "email", F.lower(e))
        .when(kind == "secret", e)
        .when(kind == "ip", F.concat_ws(".", F.transform(F.split(e, r"\."), lambda x: x.cast("int").cast("string"))))
        .when(kind == "person", F.regexp_replace(e, rf"^(?:{_TITLE})\.?[ ]", ""))
        .when((kind == "phone") & ~e.startswith("+") & (F.length(F.regexp_replace(e, r"\D", "")) == 10), F.concat(F.lit("1"), F.regexp_replace(e, r"\D", "")))
        .otherwise(F.regexp_replace(e, r"\D", ""))
    )


def stream(key: str, kind: str, canon: Column, attempt: Column) -> Column:
    """128 hexadecimal digits from the key."""
    seed = F.concat_ws("|", F.lit(key), F.lit(kind), canon, attempt.cast("string"))
    return F.concat(F.sha2(seed, 256), F.sha2(F.concat(seed, F.lit("|+")), 256))


def _let(value: Column, then) -> Column:
    """``then(value)`` with the value worked out once, however often it is used."""
    return F.get(F.transform(F.array(value), then), F.lit(0))


def _byte(s: Column, i: Column | int) -> Column:
    """Byte ``i`` of a stream, going round."""
    i = i if isinstance(i, Column) else F.lit(i)
    return F.conv(F.substring(s, (i % 64 * 2 + 1).cast("int"), F.lit(2)), 16, 10).cast("int")


def _chars(text: Column, change) -> Column:
    """The characters of a text, each changed by (character, position)."""
    return F.array_join(F.transform(F.filter(F.split(text, ""), lambda c: c != ""), change), "")


def _pick(alphabet: str, n: Column) -> Column:
    return F.substring(F.lit(alphabet), (n % len(alphabet) + 1).cast("int"), F.lit(1))


def _alike(s: Column, text: Column, hexadecimal: Column | None = None) -> Column:
    """Digits for digits, letters for letters of the same case; hexadecimal letters where all of the text is hexadecimal."""
    hexadecimal = F.lit(False) if hexadecimal is None else hexadecimal
    low, high = "abcdefghijklmnopqrstuvwxyz", "ABCDEFGHIJKLMNOPQRSTUVWXYZ"

    def change(v: Column):
        return lambda c, i: (
            F.when(hexadecimal & c.rlike("[0-9a-f]"), _pick("0123456789abcdef", _byte(v, i) + i))
            .when(hexadecimal & c.rlike("[0-9A-F]"), _pick("0123456789ABCDEF", _byte(v, i) + i))
            .when(c.rlike("[0-9]"), _pick("0123456789", _byte(v, i) + i))
            .when(c.rlike("[a-z]"), _pick(low, _byte(v, i) + i))
            .when(c.rlike("[A-Z]"), _pick(high, _byte(v, i) + i))
            .otherwise(c)
        )

    return _let(s, lambda v: _chars(text, change(v)))


def _digits(s: Column, n: Column) -> Column:
    return _let(s, lambda v: F.array_join(F.transform(F.sequence(F.lit(0), n - 1), lambda i: ((_byte(v, i) + i) % 10).cast("string")), ""))


def _luhn(digits: Column) -> Column:
    """Luhn sum of digits of which the last is the check digit."""
    n = F.length(digits)
    ds = F.transform(F.filter(F.split(digits, ""), lambda c: c != ""), lambda c, i: F.when((n - i) % 2 == 0, c.cast("int") * 2 - F.when(c.cast("int") > 4, 9).otherwise(0)).otherwise(c.cast("int")))
    return F.aggregate(ds, F.lit(0), lambda a, x: a + x)


def _formatted(e: Column, digits: Column, skip: Column) -> Column:
    """The digits after the first ``skip`` written over those of ``e``, which keeps its other characters."""
    return _let(digits, lambda d: _written(e, d, skip))


def _written(e: Column, digits: Column, skip: Column) -> Column:
    start = F.struct(F.lit("").alias("out"), F.lit(0).alias("k"))
    step = lambda a, c: F.when(c.rlike("[0-9]"), F.struct(F.concat(a["out"], F.when(a["k"] < skip, c).otherwise(F.substring(digits, a["k"] + 1, F.lit(1)))).alias("out"), (a["k"] + 1).alias("k"))).otherwise(F.struct(F.concat(a["out"], c).alias("out"), a["k"].alias("k")))
    return F.aggregate(F.filter(F.split(e, ""), lambda c: c != ""), start, step)["out"]


def _name(key: str, claim: Column, attempt: Column, gender: Column) -> Column:
    """A surrogate of one part of a name: a given name of the gender, or a family name, in the part's script and case.

    Every attempt adds a name or a syllable, so that the space outgrows the parts that collide.
    """
    part, given = claim["canon"], claim["kind"] == "given"

    def of(script: str) -> Column:
        syllables = F.array(*map(F.lit, SYLLABLES[script]))
        drawn = lambda v, names, n: F.transform(F.sequence(F.lit(0), n), lambda i: F.element_at(names, (_byte(v, i) % 16 + 1).cast("int")))
        made = _let(stream(key, "family", part, attempt), lambda v: F.initcap(F.array_join(drawn(v, syllables, attempt + 4), "")))
        several = lambda names: _let(stream(key, "given", part, attempt), lambda v: F.array_join(drawn(v, names, attempt), "-"))
        pools = [several(F.array(*map(F.lit, GIVEN[script][x]))) for x in "mfn"]
        return F.when(given, F.when(gender == "m", pools[0]).when(gender == "f", pools[1]).otherwise(pools[2])).otherwise(made)

    name = F.when(part.rlike(r"\p{IsCyrillic}"), of("cyrillic")).when(part.rlike(r"\p{IsGreek}"), of("greek")).otherwise(of("latin"))
    loud = (F.length(claim["mention"]) > 1) & (claim["mention"] == F.upper(claim["mention"]))
    return F.when(loud, F.upper(name)).otherwise(name)


def gender_of(e: Column) -> Column:
    title = F.regexp_extract(e, rf"^({_TITLE})\.?[ ]", 1)
    return F.when(title.isin(*MALE), F.lit("m")).when(title.isin(*FEMALE), F.lit("f")).otherwise(F.lit("n"))


def claimed(kind: Column, canon: Column, e: Column) -> Column:
    """What must have a surrogate of its own, as an array of (kind, canon, mention, gender): the parts of a name, or else the entity."""
    parts = F.split(canon, " ")
    last = F.size(parts) - 1
    part = lambda p, i: F.struct(F.when(i < last, "given").otherwise("family").alias("kind"), F.lower(p).alias("canon"), p.alias("mention"), F.when(i < last, gender_of(e)).alias("gender"))
    whole = F.struct(kind.alias("kind"), canon.alias("canon"), e.alias("mention"), F.lit(None).cast("string").alias("gender"))
    return F.when(kind == "person", F.transform(parts, part)).otherwise(F.array(whole))


def _power(n: Column) -> Column:
    return F.rpad(F.lit("1"), n + 1, "0").cast("long")


def _phone(key: str, canon: Column, attempt: Column) -> Column:
    """The digits of a phone number with those after the country code changed."""
    code = F.regexp_extract(canon, COUNTRY, 0)
    free = F.substring(canon, F.length(code) + 1, F.length(canon))
    d = F.length(free)
    # x -> a x + b with a = 1 and b <> 0 modulo ten: a permutation without fixed points.
    s = stream(key, "short phone", F.concat_ws("|", code, d.cast("string")), F.lit(0))
    number = lambda i, n: F.conv(F.substring(s, i, n), 16, 10).cast("long")
    a, b = number(1, 5) * 10 + 1, number(6, 5) * 10 + number(11, 5) % 9 + 1
    short = F.lpad(((a * free.cast("long") + b) % _power(d)).cast("string"), d, "0")
    drawn = F.substring(_digits(stream(key, "phone", canon, attempt), F.length(canon)), F.length(code) + 1, F.length(canon))
    return F.concat(code, F.when(d == 0, F.lit("")).when(d <= SHORT, short).otherwise(drawn))


def settled(kind: Column, canon: Column) -> Column:
    """Whether a surrogate is distinct by its making and needs no check."""
    return (kind == "phone") & (F.length(F.regexp_replace(canon, COUNTRY, "")) <= SHORT)


def surrogate(key: str, kind: Column, canon: Column, e: Column, attempt: Column) -> Column:
    """The surrogate of a mention ``e`` of anything but a person."""
    of = lambda k: stream(key, k, canon, attempt)
    n = F.length(canon)
    local = F.regexp_extract(e, "^([^@]*)@", 1)
    domain = F.concat(_alike(of("domain"), F.rpad(F.lit("host"), F.greatest(attempt, F.lit(7)), "x")), F.lit(".example."), F.element_at(F.array(F.lit("com"), F.lit("org"), F.lit("net")), (_byte(of("domain"), 20) % 3 + 1).cast("int")))
    email = F.concat(_alike(of("email"), local), F.lit("@"), domain)
    # A secret with hardly a letter or digit has too few look-alikes: later attempts change every character, then add some.
    plain = F.when(attempt < 4, e).otherwise(F.rpad(F.regexp_replace(e, "[^0-9A-Za-z]", "x"), (F.length(e) + attempt - 4).cast("int"), "x"))
    secret = _alike(of("secret"), plain, e.rlike("^[0-9a-f]+$") | e.rlike("^[0-9A-F]+$"))
    ip = _let(of("ip"), lambda v: F.concat_ws(".", (_byte(v, 0) % 15 + 240).cast("string"), *[(_byte(v, i) % 256).cast("string") for i in (1, 2, 3)]))
    ssn = _formatted(e, F.concat(F.lit("9"), _digits(of("ssn"), F.lit(8))), F.lit(0))
    off = F.when(_luhn(canon) % 10 == 0, F.lit(0)).otherwise(_byte(of("card"), 40) % 9 + 1)
    body = F.concat(F.substring(canon, F.lit(1), F.lit(1)), _digits(of("card"), n - 2))
    whole = _let(body, lambda b: F.concat(b, (((10 - _luhn(F.concat(b, F.lit("0"))) % 10) % 10 + off) % 10).cast("string")))
    card = _formatted(e, whole, F.lit(0))
    written = F.length(F.regexp_replace(e, r"\D", ""))
    phone = _formatted(e, _let(_phone(key, canon, attempt), lambda x: F.substring(x, n - written + 1, written)), F.lit(0))
    return F.when(kind == "email", email).when(kind == "secret", secret).when(kind == "ip", ip).when(kind == "ssn", ssn).when(kind == "card", card).otherwise(phone)


def mentions(text: Column) -> Column:
    """All mentions in order; null for texts that the gate rules out."""
    return F.when(text.rlike(GATE), F.regexp_extract_all(text, F.lit(PATTERN), F.lit(0)))


def entities(docs: DataFrame, text: str = "text") -> DataFrame:
    """kind, canon and one mention of every distinct entity, persons by gender; mentions are counted before they are shuffled."""
    found = docs.select(F.explode(mentions(F.col(text))).alias("mention")).groupBy("mention").count()
    typed = found.withColumn("kind", kind_of(F.col("mention"))).withColumn("canon", canonical(F.col("kind"), F.col("mention")))
    gender = F.when(F.col("kind") == "person", gender_of(F.col("mention"))).alias("gender")
    return typed.groupBy("kind", "canon", gender).agg(F.min("mention").alias("mention"), F.sum("count").alias("mentions")).drop("gender")


def redrawn(known: DataFrame, key: str = KEY, attempts: int = ATTEMPTS) -> DataFrame:
    """kind, canon, attempt, gender of the entities whose first surrogate collides with another's or with a real entity, and of given
    names before which titles differ. Persons are checked and redrawn by part (kind ``given`` or ``family``)."""
    claims = known.select(F.explode(claimed(F.col("kind"), F.col("canon"), F.col("mention"))).alias("x")).select("x.*")
    told = {x: F.coalesce(F.max(F.col("gender") == x), F.lit(False)) for x in "mf"}
    gender = F.when(told["m"] & ~told["f"], "m").when(told["f"] & ~told["m"], "f").otherwise("n")
    real = checkpointed(claims.groupBy("kind", "canon").agg(F.min("mention").alias("mention"), gender.alias("gender"), (F.count_distinct("gender") > 1).alias("differ")))
    part = F.col("kind").isin("given", "family")
    name = _name(key, F.struct("kind", "canon", F.col("canon").alias("mention")), F.col("attempt"), F.col("gender"))
    whole = surrogate(key, F.col("kind"), F.col("canon"), F.col("mention"), F.col("attempt"))
    written = F.when(part, name).otherwise(whole)
    form = F.when(part, F.lower("written")).otherwise(canonical(F.col("kind"), F.col("written")))
    fixed = ["kind", "canon", "mention", "gender", "differ", "attempt"]

    def drawn(rows: DataFrame) -> DataFrame:
        """The rows with the form of their surrogate."""
        return checkpointed(rows.withColumn("written", written).withColumn("made", form).drop("written"))

    free = real.where(~settled(F.col("kind"), F.col("canon")))
    made, rounds = drawn(free.withColumn("attempt", F.lit(0))), 0
    while True:
        # Of those that share a surrogate the least form keeps it, unless it was settled on in an earlier round.
        claims = made.groupBy("kind", "made").agg(F.min(F.struct((F.col("attempt") > 0).alias("late"), "canon")).alias("first"), F.count(F.lit(1)).alias("n"))
        taken = claims.where("n > 1").select("kind", "made", F.col("first.canon").alias("keeper"))
        shared = made.join(taken, ["kind", "made"]).where("canon <> keeper").select(fixed)
        itself = made.join(free.select("kind", F.col("canon").alias("made")), ["kind", "made"], "left_semi").select(fixed)
        again = drawn(shared.union(itself).distinct().withColumn("attempt", F.col("attempt") + 1))
        if again.isEmpty():
            return made.where("attempt > 0 OR differ").select("kind", "canon", "attempt", "gender")
        if (rounds := rounds + 1) > attempts:
            raise RuntimeError(f"surrogates still collide after {attempts} rounds, such as {again.first()['kind']}")
        made = checkpointed(made.join(again.select("kind", "canon"), ["kind", "canon"], "left_anti").select(again.columns).union(again))


def replaced(docs: DataFrame, key: str = KEY, text: str = "text", exceptions: DataFrame | None = None) -> DataFrame:
    """The rows of ``docs`` with every entity of ``text`` replaced, and their number in ``n_entities``."""
    exceptions = redrawn(entities(docs, text), key) if exceptions is None else exceptions
    pair, value = F.concat_ws("|", "kind", "canon"), F.concat_ws(",", F.col("attempt").cast("string"), F.coalesce("gender", F.lit("")))
    few = exceptions.select(pair.alias("k"), value.alias("v")).limit(LITERAL + 1).collect()
    found = docs
    if len(few) > LITERAL:
        at = docs.select(F.xxhash64(text).alias("__text"), F.explode(F.array_distinct(mentions(F.col(text)))).alias("mention")).distinct()
        typed = at.withColumn("kind", kind_of(F.col("mention"))).withColumn("canon", canonical(F.col("kind"), F.col("mention")))
        claims = typed.select("__text", F.explode(claimed(F.col("kind"), F.col("canon"), F.col("mention"))).alias("x")).select("__text", "x.*").drop("gender")
        maps = claims.join(exceptions, ["kind", "canon"]).groupBy("__text").agg(F.map_from_entries(F.collect_set(F.struct(pair.alias("k"), value.alias("v")))).alias("__tries"))
        found = found.withColumn("__text", F.xxhash64(text)).join(maps, "__text", "left").drop("__text")
    elif few:
        found = found.withColumn("__tries", F.from_json(F.lit(json.dumps({r["k"]: r["v"] for r in few})), "map<string,string>"))

    # One column a step, so that nothing is written out twice inside the next. Only texts with an entity are cut.
    first = found.withColumn("__found", mentions(F.col(text)))
    # In a text with titled persons the parts of their names are looked for as well.
    person = lambda e: claimed(F.lit("person"), canonical(F.lit("person"), e), e)
    told = first.withColumn("__told", F.array_distinct(F.flatten(F.transform(F.filter("__found", is_person), person))))
    parts = F.array_distinct(F.transform("__told", lambda c: c["mention"]))
    wide = F.concat(F.lit(PATTERN + r"|(?<!\p{L})(?=\p{Lu})(?:"), F.array_join(parts, "|"), F.lit(r")(?![\p{L}'-])"))
    named = told.withColumn("__wide", F.when(F.size("__told") > 0, wide))
    both = named.withColumn("__found", F.when(F.col("__wide").isNotNull(), F.regexp_extract_all(F.col(text), F.col("__wide"), F.lit(0))).otherwise(F.col("__found")))
    pieces = F.when(F.col("__wide").isNotNull(), F.split(F.col(text), F.col("__wide"), -1)).otherwise(F.split(F.col(text), PATTERN, -1))
    both = both.withColumn("__cut", F.when(F.size("__found") > 0, pieces))

    named_part = lambda e: F.exists("__told", lambda c: c["mention"] == e)
    kinds = both.withColumn("__found", F.transform("__found", lambda e: F.struct(e.alias("e"), F.when(F.size("__told") > 0, F.when(named_part(e), "part").otherwise(kind_of(e))).otherwise(kind_of(e)).alias("kind"))))
    forms = kinds.withColumn("__found", F.transform("__found", lambda x: F.struct(x["e"].alias("e"), x["kind"].alias("kind"), canonical(x["kind"], x["e"]).alias("canon"))))
    tries = (lambda kind, canon: F.coalesce(F.col("__tries")[F.concat_ws("|", kind, canon)], F.lit("0,"))) if few else (lambda *_: F.lit("0,"))
    attempt = lambda v: F.substring_index(v, ",", 1).cast("int")

    def part(c: Column) -> Column:
        """One part of a name."""
        return _let(tries(c["kind"], c["canon"]), lambda v: _name(key, c, attempt(v), F.coalesce(F.nullif(F.substring_index(v, ",", -1), F.lit("")), c["gender"])))

    def rewritten(x: Column) -> Column:
        title = F.regexp_extract(x["e"], rf"^((?:{_TITLE})\.?[ ])", 1)
        whole = F.concat(title, F.array_join(F.transform(person(x["e"]), part), " "))
        alone = part(F.get(F.filter("__told", lambda c: c["mention"] == x["e"]), F.lit(0)))
        rest = surrogate(key, x["kind"], x["canon"], x["e"], attempt(tries(x["kind"], x["canon"])))
        return F.when(x["kind"] == "person", whole).when(x["kind"] == "part", alone).otherwise(rest)

    made = forms.withColumn("__found", F.transform("__found", rewritten))
    # One piece more than entities: each piece is followed by a surrogate, the last by nothing.
    rebuilt = F.array_join(F.zip_with("__cut", "__found", lambda p, s: F.concat(p, F.coalesce(s, F.lit("")))), "")
    out = F.when(F.size("__found") > 0, rebuilt).otherwise(F.col(text))
    return made.withColumn(text, out).withColumn("n_entities", F.coalesce(F.size("__found"), F.lit(0))).select(*[c for c in docs.columns if c != "n_entities"], "n_entities")
