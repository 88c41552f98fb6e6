"""Personal data and secrets replaced by surrogates.

Entities are found by one pattern: e-mail addresses, keys and passwords, network addresses, account, card, social security and
phone numbers, and names after a form of address or with a common given name. Each gets a surrogate that a secret key and the entity's normal form alone
decide, of the same type: a phone number keeps its punctuation, its country code and its count of digits, a card or account number its first
characters and right check digits, an address valid octets, a key its prefix and alphabet, a name its form of address, its gender and its script. Texts without any sign of an entity are not scanned.

Coreference: all mentions with one normal form (digits of numbers, of phone numbers without the country code; lower case of addresses; of names the given and the family name each) get one surrogate, in every document: "John Smith",
"Dr. Smith" and "Mr. John Smith" share theirs. A full name has the gender that any of its mentions tells, else its given name's.
Distinctness: over all entities of the table, no two are written alike and none is written as an entity of the table; who loses such a clash tries its next surrogate. It is checked on what is written: digits
after the country code, given and family names.
Only entities are shuffled for that; texts are rewritten where they are read. Documents are joined with attempts, and with genders that only another mention tells, for the entities that need them alone.

Edge cases: a null text stays null, an empty one empty; a text of any length is scanned by linear patterns; ties between genders of one full name go to the female one; repeated rows come out alike; an empty table gives an
empty table; other columns are carried through untouched, but for one of the name that `count` gives, which is replaced; names that begin with `__` are the operator's own.
"""

from __future__ import annotations

import secrets

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from graphslices.llm.common import cut, let

_OCTET = r"(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[1-9]?[0-9])"
_SECRET_NAME = r"(?i:password|passwd|secret|token|api[_-]?key)"
# Forms of address, by the gender they tell.
MALE = ("Mr", "Herr", "Señor", "Sr", "Monsieur", "Г-н")
FEMALE = ("Mrs", "Ms", "Frau", "Señora", "Sra", "Mme", "Madame", "Г-жа")
OPEN = ("Dr", "Prof")
# Common given names.
KNOWN_MALE = ("John", "James", "Robert", "Michael", "William", "David", "Richard", "Thomas", "Peter", "Paul", "Mark", "Daniel", "Hans", "Klaus", "Jürgen", "Stefan", "Andreas", "Juan", "José", "Carlos", "Luis", "Miguel", "Pedro", "Jean", "Pierre", "Michel", "Philippe", "Иван", "Пётр", "Сергей", "Алексей")
KNOWN_FEMALE = ("Mary", "Patricia", "Jennifer", "Linda", "Elizabeth", "Susan", "Sarah", "Anna", "Karen", "Laura", "Maria", "María", "Carmen", "Ana", "Isabel", "Lucía", "Sabine", "Petra", "Monika", "Ursula", "Marie", "Sophie", "Catherine", "Claire", "Ольга", "Елена", "Мария", "Наталья")
_PART = r"\p{Lu}\p{Ll}+(?:[-'’]\p{Lu}\p{Ll}+)?"
_TITLE = f"(?:{'|'.join(sorted(MALE + FEMALE + OPEN, key=len, reverse=True))})"
PATTERNS = {
    "email": r"(?<![\p{L}\p{N}._%+-])[\p{L}\p{N}._%+-]++@(?:[\p{L}\p{N}-]+\.)+\p{L}{2,}",
    "key": r"\bAKIA[0-9A-Z]{16}\b",
    "secret": _SECRET_NAME + r"\s{0,3}[=:]\s{0,3}[\"']?[^\s\"'&,;]{6,}",
    "hex": r"(?<![0-9A-Za-z])[0-9a-f]{32,64}(?![0-9A-Za-z])",
    "ip": rf"(?<![0-9.])(?:{_OCTET}\.){{3}}{_OCTET}(?!\.?[0-9])",
    "ssn": r"(?<![0-9-])[0-9]{3}-[0-9]{2}-[0-9]{4}(?![0-9-])",
    "iban": r"\b[A-Z]{2}[0-9]{2}(?: ?[A-Z0-9]{4}){2,7}(?: ?[A-Z0-9]{1,3})?\b",
    "card": r"(?<![0-9.])(?:[0-9][ -]?){12,18}[0-9](?![0-9])",
    "phone": r"(?<![0-9+])(?:\+[0-9]{1,3}[ .-]?)?(?:\([0-9]{2,4}\)[ .-]?|[0-9]{2,4}[ .-])[0-9]{3,4}[ .-][0-9]{3,4}(?![0-9])",
    "name": rf"(?=\p{{Lu}})(?<!\p{{L}})(?:{_TITLE}\.?\s{_PART}(?:\s{_PART})?|(?:{'|'.join(KNOWN_MALE + KNOWN_FEMALE)})\s{_PART})(?!\p{{L}})",
}
# What every entity but a name has somewhere: a digit, a sign of an address or of a named secret, letters of a digest; and what every name has: a capital after another capitalised word.
SIGN = r"[0-9@=:]|[a-f]{32}"
NAME_SIGN = r"(?:\p{Lu}\p{Ll}*|Г-\p{Ll}+)\.?\s\p{Lu}\p{Ll}"
ANY = "|".join(f"(?:{p})" for p in PATTERNS.values())
# Syllables of names, by script, and what given names of a gender end in.
SYLLABLES = {"latin": ("ba", "do", "fe", "gu", "hi", "ka", "lo", "me", "nu", "pi", "ra", "so", "te", "vu", "wi", "za"), "cyrillic": ("ба", "до", "ге", "жу", "ки", "ла", "мо", "не", "пу", "ри", "са", "то", "фе", "ху", "ши", "за")}
ENDINGS = {"latin": {"m": ("n", "rt", "ck", "s"), "f": ("na", "lia", "ra", "nda")}, "cyrillic": {"m": ("н", "р", "й", "м"), "f": ("на", "лия", "ра", "нда")}}


def entities(text: Column) -> Column:
    found = lambda pattern: F.regexp_extract_all(text, F.lit(pattern), F.lit(0))
    # without a sign of another kind, names are all that can be found
    return F.when(text.rlike(SIGN), found(ANY)).when(text.rlike(NAME_SIGN), found(PATTERNS["name"])).otherwise(F.array().cast("array<string>"))


def kind_of(e: Column) -> Column:
    digits = F.length(F.regexp_replace(e, "[^0-9]", ""))
    out = F.when(e.contains("@"), "email")
    for kind in ("key", "secret", "hex", "ip", "ssn", "name"):
        out = out.when(e.rlike(f"^(?:{PATTERNS[kind]})$"), kind)
    return out.when(e.rlike("^[A-Z]{2}[0-9]{2}"), "iban").when((digits >= 13) & ~e.rlike(r"[+(]"), "card").otherwise("phone")


def _value(e: Column) -> Column:
    """Of a named secret its value, of a name what follows the form of address."""
    return F.regexp_replace(F.regexp_replace(e, f"^{_SECRET_NAME}\\s*[=:]\\s*[\"']?", ""), rf"^{_TITLE}\.?\s", "")


def country_code(e: Column) -> Column:
    return F.regexp_extract(e, r"^\+([0-9]{1,3})(?:[ .-]|\()", 1)


def normal(e: Column, kind: Column) -> Column:
    """The form in which mentions of one entity are equal."""
    digits = F.regexp_replace(e, "[^0-9]", "")
    return (
        F.when(kind == "email", F.lower(e)).when(kind == "phone", F.substring(digits, F.length(country_code(e)) + 1, F.length(e))).when(kind.isin("card", "ssn"), digits)
        .when(kind == "iban", F.replace(e, F.lit(" "), F.lit(""))).when(kind == "name", F.array_join(F.split(_value(e), r"\s"), " "))
        .when(kind == "secret", _value(e)).otherwise(e)
    )


def told_gender(e: Column) -> Column:
    """The gender that a form of address tells, or null."""
    return F.when(e.rlike(f"^(?:{'|'.join(FEMALE)})\\b"), "f").when(e.rlike(f"^(?:{'|'.join(MALE)})\\b"), "m")


def usual_gender(given: Column) -> Column:
    return F.when(given.isin(*KNOWN_FEMALE), "f").when(given.isin(*KNOWN_MALE), "m").when(given.rlike("[aeiая]$"), "f").otherwise("m")


def name_parts(name: Column, gender: Column) -> Column:
    """(kind, norm) of the given and the family name of a name's normal form. A given name's begins with its gender."""
    given, family = F.substring_index(name, " ", 1), F.substring_index(name, " ", -1)
    part = lambda kind, norm: F.struct(F.lit(kind).alias("kind"), norm.alias("norm"))
    first = part("given", F.concat(gender, F.lit(":"), given))
    alone = F.when(given.isin(*KNOWN_MALE, *KNOWN_FEMALE), first).otherwise(part("family", family))
    return F.when(F.instr(name, " ") > 0, F.array(first, part("family", family))).otherwise(F.array(alone))


def shown(kind: Column, norm: Column) -> Column:
    """What a text shows of a normal form: clashes are told by this."""
    return F.when(kind == "given", F.substring(norm, F.lit(3), F.length(norm))).otherwise(norm)


def _pick(choices: str | tuple, seed: Column, i: Column) -> Column:
    at = F.pmod(F.xxhash64(seed, i), F.lit(len(choices))).cast("int")
    return F.substring(F.lit(choices), at + 1, F.lit(1)) if isinstance(choices, str) else F.get(F.array(*map(F.lit, choices)), at)


def _alike(value: Column, seed: Column, keep: int | Column = 0) -> Column:
    """value with every letter and digit after the first `keep` replaced by one of its class and script."""
    hexes = value.rlike("^[0-9a-f]+$") & value.rlike("[a-f]")

    def char(c: Column, i: Column) -> Column:
        return (
            F.when(i < keep, c).when(hexes & c.rlike("[0-9a-f]"), _pick("0123456789abcdef", seed, i))
            .when(c.rlike("[0-9]"), _pick("0123456789", seed, i))
            .when(c.rlike(r"[\p{IsCyrillic}&&\p{Lu}]"), _pick("АБВГДЕЖЗИКЛМНОПРСТУФХЦЧШЭЮЯ", seed, i)).when(c.rlike(r"\p{IsCyrillic}"), _pick("абвгдежзиклмнопрстуфхцчшэюя", seed, i))
            .when(c.rlike(r"[\p{IsGreek}&&\p{Lu}]"), _pick("ΑΒΓΔΕΖΗΘΙΚΛΜΝΞΟΠΡΣΤΥΦΧΨΩ", seed, i)).when(c.rlike(r"\p{IsGreek}"), _pick("αβγδεζηθικλμνξοπρστυφχψω", seed, i))
            .when(c.rlike(r"\p{Lu}"), _pick("ABCDEFGHIJKLMNOPQRSTUVWXYZ", seed, i)).when(c.rlike(r"\p{L}"), _pick("abcdefghijklmnopqrstuvwxyz", seed, i)).otherwise(c)
        )

    return F.array_join(F.transform(F.split(value, ""), char), "")


def _checked(digits: Column) -> Column:
    """digits with the last one set so that the number passes the card check sum."""
    body = F.reverse(F.split(F.substring(digits, F.lit(1), F.length(digits) - 1), ""))

    def weight(c: Column, i: Column) -> Column:
        d = c.cast("int")
        return F.when(i % 2 == 1, d).when(d >= 5, 2 * d - 9).otherwise(2 * d)

    total = F.aggregate(F.transform(body, weight), F.lit(0), lambda a, x: a + x)
    return F.concat(F.substring(digits, F.lit(1), F.length(digits) - 1), ((10 - total % 10) % 10).cast("string"))


def _account(norm: Column) -> Column:
    """An account number with the two check digits that its other characters ask for."""
    moved = F.concat(F.substring(norm, F.lit(5), F.length(norm)), F.substring(norm, 1, 2), F.lit("00"))

    def step(rest: Column, c: Column) -> Column:
        value = F.instr(F.lit("0123456789ABCDEFGHIJKLMNOPQRSTUVWXYZ"), c) - 1
        return F.when(value > 9, (rest * 100 + value) % 97).otherwise((rest * 10 + value) % 97)

    rest = F.aggregate(F.split(moved, ""), F.lit(0), step)
    return F.concat(F.substring(norm, 1, 2), F.lpad((98 - rest).cast("string"), 2, "0"), F.substring(norm, F.lit(5), F.length(norm)))


def _name(kind: Column, norm: Column, seed: Column, attempt: Column) -> Column:
    """A given name with an ending of its gender, or a family name, of syllables of its script."""
    def script(key: str) -> Column:
        syllables = lambda n: F.initcap(F.array_join(F.transform(F.sequence(F.lit(1), n + attempt), lambda i: _pick(SYLLABLES[key], seed, i)), ""))
        ends = F.when(F.substring(norm, 1, 1) == "m", _pick(ENDINGS[key]["m"], seed, F.lit(-1))).otherwise(_pick(ENDINGS[key]["f"], seed, F.lit(-1)))
        return F.when(kind == "given", F.concat(F.substring(norm, 1, 2), syllables(2), ends)).otherwise(syllables(3))

    return F.when(norm.rlike(r"\p{IsCyrillic}"), script("cyrillic")).otherwise(script("latin"))


def surrogate(kind: Column, norm: Column, attempt: Column, key: str) -> Column:
    """The surrogate's normal form."""
    seed = F.sha2(F.concat_ws("\x1f", F.lit(key), kind, norm, attempt.cast("string")), 256)
    domain = F.substring_index(norm, "@", -1)
    host = F.sha2(F.concat_ws("\x1f", F.lit(key), F.lit("domain"), domain), 256)
    email = F.concat(_alike(F.substring_index(norm, "@", 1), seed), F.lit("@"), _alike(F.regexp_replace(domain, r"\.[^.]*$", ""), host), F.lit(".example"))
    email = F.when(F.length(F.regexp_replace(F.substring_index(norm, "@", 1), "[^a-z0-9]", "")) + attempt >= 4, email).otherwise(
        F.concat(F.substring(seed, F.lit(1), 4 + attempt), F.lit("."), email)
    )
    octets = F.array_join(F.transform(F.sequence(F.lit(1), F.lit(4)), lambda i: (F.pmod(F.xxhash64(seed, i), F.lit(254)) + 1).cast("string")), ".")
    return (
        F.when(kind == "email", email).when(kind == "ip", octets).when(kind == "card", _checked(_alike(norm, seed, 1)))
        .when(kind == "key", _alike(norm, seed, 4)).when(kind == "iban", _account(_alike(norm, seed, 2))).when(kind.isin("given", "family"), _name(kind, norm, seed, attempt))
        .otherwise(_alike(norm, seed))
    )


def rendered(e: Column, kind: Column, new: Column) -> Column:
    """A mention e with the surrogate new, as it is shown, in the mention's own format."""
    full = F.when(kind == "phone", F.concat(country_code(e), new)).otherwise(new)

    def place(c: Column, i: Column) -> Column:
        k = F.length(F.regexp_replace(F.substring(e, F.lit(1), i + 1), "[^0-9A-Z]", ""))
        return F.when(c.rlike("[0-9A-Z]"), F.substring(full, k, F.lit(1))).otherwise(c)

    filled = F.array_join(F.transform(F.split(e, ""), place), "")
    front = F.substring(e, F.lit(1), F.length(e) - F.length(_value(e)))
    between = F.regexp_extract(_value(e), r"\s", 0)
    return (
        F.when(kind.isin("phone", "card", "ssn", "iban"), filled).when(kind == "secret", F.concat(front, new))
        .when(kind == "name", F.concat(front, F.replace(new, F.lit(" "), between))).otherwise(new)
    )


def attempts(docs: DataFrame, key: str, text: str = "text") -> DataFrame | None:
    """(kind, norm, how) of the entities that are not rendered as they stand: the attempt of those whose first surrogate clashed, and the gender of full names (kind `person`) that other mentions tell; None if there are none."""
    e, kind = F.col("e"), F.col("kind")
    found = docs.select(F.explode(F.array_distinct(entities(F.col(text)))).alias("e")).withColumn("kind", kind_of(e))
    found = found.withColumns({"norm": normal(e, kind), "told": F.when(kind == "name", told_gender(e))})
    found = cut(found.groupBy("kind", "norm").agg(F.min("told").alias("told")))
    usual = usual_gender(F.substring_index("norm", " ", 1))
    people = found.where(kind == "name").withColumn("gender", F.coalesce("told", usual))
    known = found.where(kind != "name").select("kind", "norm").unionByName(people.select(F.explode(name_parts(F.col("norm"), F.col("gender"))).alias("x")).select("x.*"))
    known = cut(known.distinct())
    genders = people.where(F.col("gender") != usual).select(F.lit("person").alias("kind"), "norm", F.col("gender").alias("how"))
    trying, done = known.withColumn("attempt", F.lit(0)), None
    while True:
        tried = cut(trying.withColumn("new", let(surrogate(kind, F.col("norm"), F.col("attempt"), key), lambda new: shown(kind, new))))
        real = known.select("kind", shown(kind, F.col("norm")).alias("new"))
        taken = real if done is None else real.unionByName(done.select("kind", "new"))
        free = tried.join(taken, ["kind", "new"], "left_anti")
        won = free.groupBy("kind", "new").agg(F.min("norm").alias("norm"))
        lost = cut(tried.join(won, ["kind", "new", "norm"], "left_anti").select("kind", "norm", (F.col("attempt") + 1).alias("attempt")))
        if done is None and lost.isEmpty():
            return None if genders.isEmpty() else genders
        won = won.join(tried.select("kind", "norm", "attempt"), ["kind", "norm"]).select("kind", "norm", "attempt", "new")
        done = won if done is None else cut(done.unionByName(won))
        if lost.isEmpty():
            return done.where("attempt > 0").select("kind", "norm", F.col("attempt").cast("string").alias("how")).unionByName(genders)
        trying = lost


def surrogate_key(spark: SparkSession) -> str:
    """The secret key of the session, spark.graphslices.surrogateKey; where it has none, a random one is drawn and kept for the session, so that surrogates agree within it and differ from session to session."""
    name = "spark.graphslices.surrogateKey"
    if not spark.conf.get(name, None):
        spark.conf.set(name, secrets.token_hex(32))
    return spark.conf.get(name)


def with_surrogates(docs: DataFrame, key: str, text: str = "text", count: str | None = "n_entities") -> DataFrame:
    """docs with the entities of `text` replaced, and their number in the column `count`, if one is named."""
    again = attempts(docs, key, text)
    known = lambda e: let(kind_of(e), lambda k: F.struct(e.alias("e"), k.alias("k"), normal(e, k).alias("n"), F.when(k == "name", told_gender(e)).alias("g")))
    found = docs.withColumn("__found", F.when(F.col(text).isNotNull(), F.transform(entities(F.col(text)), known)))
    label = lambda kind, norm: F.concat(kind, F.lit(":"), norm)
    if again is None:
        found = found.withColumn("__again", F.lit(None).cast("map<string,string>"))
    else:
        def labels(x: Column) -> Column:
            parts = F.concat(F.array(F.struct(F.lit("person").alias("kind"), x["n"].alias("norm"))), *[name_parts(x["n"], F.lit(g)) for g in "mf"])
            return F.when(x["k"] == "name", F.transform(parts, lambda q: label(q["kind"], q["norm"]))).otherwise(F.array(label(x["k"], x["n"])))

        found = found.withColumn("__row", F.xxhash64("doc_id", text))
        asked = found.where(F.size("__found") > 0).select("__row", F.explode(F.array_distinct(F.flatten(F.transform("__found", labels)))).alias("name"))
        hits = asked.join(again.select(label(F.col("kind"), F.col("norm")).alias("name"), "how"), "name").distinct()
        maps = hits.groupBy("__row").agg(F.map_from_entries(F.collect_list(F.struct("name", "how"))).alias("__again"))
        found = found.join(maps, "__row", "left").drop("__row")

    def how(kind: Column, norm: Column) -> Column:
        return F.get(F.map_values(F.map_filter(F.col("__again"), lambda k, v: k == label(kind, norm))), F.lit(0))

    def written(kind: Column, norm: Column) -> Column:
        attempt = F.coalesce(how(kind, norm).cast("int"), F.lit(0))
        return let(surrogate(kind, norm, attempt, key), lambda n: shown(kind, n))

    def new(x: Column) -> Column:
        gender = F.coalesce(how(F.lit("person"), x["n"]), x["g"], usual_gender(F.substring_index(x["n"], " ", 1)))
        parts = F.when(x["k"] == "name", name_parts(x["n"], gender)).otherwise(F.array(F.struct(x["k"].alias("kind"), x["n"].alias("norm"))))
        return let(F.array_join(F.transform(parts, lambda q: written(q["kind"], q["norm"])), " "), lambda n: rendered(x["e"], x["k"], n))

    between = F.split(F.col(text), ANY, -1)
    pieces = F.zip_with(between, F.transform("__found", new), lambda a, b: F.concat(a, F.coalesce(b, F.lit(""))))
    rewritten = F.when(F.size("__found") > 0, F.array_join(pieces, "")).otherwise(F.col(text))
    return found.withColumn("__new", rewritten).withColumns(({count: F.coalesce(F.size("__found"), F.lit(0)).cast("long")} if count else {}) | {text: F.col("__new")}).drop("__found", "__again", "__new")
