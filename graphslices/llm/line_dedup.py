"""Line dedup over a whole corpus by a deletion-neighbourhood join.

A line is the sequence of its lower-cased words. Lines of `min_words` words or more are near copies when one word inserted,
removed or replaced turns one into the other; shorter lines must be equal. Of each line the earliest place, by (doc_id, line
number), stays; a line also goes if any earlier line is a near copy of it, kept or not.

How: equal lines meet by a 128-bit hash and leave their earliest place. Two lines within one edit share their first or last
half, so only lines whose half occurs in another line go on. Those emit every variant with one word of the other half
deleted, as hashed keys, beside the line itself. Equal keys name the earliest line that produced them; each line is checked
against that one by word edit distance. No pair of a group is formed but (line, earliest), so a key of any size costs one row a member.

Edge cases: a null or empty text comes back as it is and blank lines always stay; repeated rows with one doc_id and text count as one document and come out
alike; rows that share a doc_id but differ in text are told apart by a hash of it; a null doc_id sorts first; lines of any length
take part (above `ordered_words` words in a half, hashes of what a deletion leaves come from sums over blocks of words instead of the words anew, so that they cost n * sqrt(n) and not n * n; the links are the same);
an empty table gives an empty table; other columns are carried through, but for `n_lines` and `n_kept`, which are replaced; names that begin with `__` are the operator's own.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from graphslices.llm.common import NOT_WHITE, cut, let, words_of, written

PLACE = ("doc", "tag", "line_no")
MASK = (1 << 62) - 1


@dataclass(frozen=True)
class LineBound:
    min_words: int = 8
    ordered_words: int = 2000


def _lines(docs: DataFrame, text: str) -> DataFrame:
    return docs.select(
        F.col("doc_id").alias("doc"), F.xxhash64(text).alias("tag"), F.posexplode(F.split(text, "\n")).alias("line_no", "line")
    )


def _halves(words: Column, bound: LineBound) -> Column:
    """(side, length, hash) of the first and last halves a near copy can share with the line: side 0 is the front."""
    n = F.size(words)

    def of(m: Column) -> list[Column]:
        return [
            F.struct(F.lit(side).alias("side"), m.alias("m"), F.xxhash64(F.lit(side), m, part).alias("h"))
            for side, part in ((0, F.slice(words, 1, m)), (1, F.slice(words, n - m + 1, m)))
        ]

    def half(k: Column) -> Column:
        return F.floor(k / 2).cast("int")

    odd = F.array(*of(half(n)))
    even = F.array(*of(half(n)), *of(half(n - 1)))
    return F.when(n < bound.min_words, F.array().cast("array<struct<side:int,m:int,h:bigint>>")).when(n % 2 == 1, odd).otherwise(even)


def _places(frame: DataFrame, other: DataFrame, how: str, cols=PLACE) -> DataFrame:
    """Joins on the place columns, null doc ids being equal."""
    right = other.select(*[F.col(c).alias(f"__{c}") if c in cols else F.col(c) for c in other.columns])
    on = F.lit(True)
    for c in cols:
        on = on & F.equal_null(F.col(c), F.col(f"__{c}"))
    return frame.join(right, on, how).drop(*[f"__{c}" for c in cols])


def _first_places(docs: DataFrame, bound: LineBound, text: str) -> DataFrame:
    # the filter reads the line, not its words: it is pushed below them and would split each line again
    lines = _lines(docs, text).where(F.col("line").rlike(NOT_WHITE)).withColumn("words", words_of(F.lower("line")))
    facts = lines.select(
        F.xxhash64("words").alias("k1"), F.xxhash64(F.lit(7), F.col("words")).alias("k2"),
        F.struct(*PLACE, F.size("words").alias("n"), _halves(F.col("words"), bound).alias("halves")).alias("at"),
    )
    return facts.groupBy("k1", "k2").agg(F.min("at").alias("at")).select("at.*")


def _add(a: Column, x: Column) -> Column:
    return (a + x).bitwiseAND(F.lit(MASK))


def _width(v: Column) -> Column:
    return F.greatest(F.ceil(F.sqrt(F.size(v))), F.lit(1)).cast("int")


def _block_sums(v: Column) -> Column:
    """Sums of the numbers before each block of about sqrt(n) of them, modulo 2**62."""
    k, zero = _width(v), F.lit(0).cast("long")
    blocks = F.transform(F.sequence(F.lit(0), F.floor(F.size(v) / k).cast("int")), lambda b: F.aggregate(F.slice(v, b * k + 1, k), zero, _add))
    return let(blocks, lambda t: F.transform(t, lambda x, b: F.aggregate(F.slice(t, F.lit(1), b), zero, _add)))


def _sum_before(v: Column, sums: Column, i: Column) -> Column:
    """The sum of the first i numbers, in about sqrt(n) steps."""
    k = _width(v)
    b = F.floor(i / k).cast("int")
    return F.aggregate(F.slice(v, b * k + 1, i - b * k), F.get(sums, b), _add)


def _variants(near: DataFrame, bound: LineBound) -> DataFrame:
    """(place, kind, key): kind 0 is the line itself, 1 a deletion variant, 2 a variant that also tells where the word stood."""
    h = F.col("half")
    n = F.size("words")
    other = F.when(h["side"] == 0, F.slice("words", h["m"] + 1, n - h["m"])).otherwise(F.slice("words", F.lit(1), n - h["m"]))
    def keys(g: Column) -> Column:
        q = F.size(g)
        short = F.transform(g, lambda x, i: F.struct(i.alias("i"), F.xxhash64(F.concat(F.slice(g, F.lit(1), i), F.slice(g, i + 2, q))).alias("r")))

        def emitted(gone: Column, whole: Column) -> Column:
            row = lambda kind, key: F.struct(F.lit(kind).alias("kind"), key.alias("key"))
            none = F.array().cast("array<struct<kind:int,key:bigint>>")
            cuts = F.concat(F.array(row(0, F.xxhash64(h["h"], whole))), F.array_distinct(F.transform(gone, lambda x: row(1, F.xxhash64(h["h"], x["r"])))))
            places = F.transform(gone, lambda x: row(2, F.xxhash64(h["h"], x["i"], q, x["r"])))
            return F.concat(F.when(h["uneven"], cuts).otherwise(none), F.when(h["same"], places).otherwise(none))

        def long(here: Column, back: Column) -> Column:
            """A rest's hash as a sum over its words and their places in it: the words before the gone one keep theirs, those after it move back by one."""
            upto = lambda x, i: _sum_before(x["v"], x["s"], i)
            gone = F.transform(g, lambda x, i: F.struct(i.alias("i"), (upto(here, i) + upto(back, q) - upto(back, i + 1)).bitwiseAND(F.lit(MASK)).alias("r")))
            return let(F.when(q - 1 <= bound.ordered_words, short).otherwise(gone), lambda x: emitted(x, upto(here, q)))

        placed = lambda move: let(F.transform(g, lambda x, i: F.xxhash64(x, i - move).bitwiseAND(F.lit((1 << 48) - 1))), lambda v: F.struct(v.alias("v"), _block_sums(v).alias("s")))
        return F.when(q <= bound.ordered_words, let(short, lambda x: emitted(x, F.xxhash64(g)))).otherwise(let(placed(0), lambda here: let(placed(1), lambda back: long(here, back))))

    hashes = F.transform(other, lambda w: F.xxhash64(w))
    return near.withColumn("half", F.explode("halves")).select(*PLACE, F.inline(let(hashes, keys)))


def one_edit(a: Column, b: Column) -> Column:
    """Whether one word inserted, removed or replaced turns words a into words b."""
    na, nb = F.size(a), F.size(b)
    short, long = F.when(na <= nb, a).otherwise(b), F.when(na <= nb, b).otherwise(a)

    def after(p: Column) -> Column:
        n = F.least(na, nb)
        replaced = F.slice(a, p + 1, n) == F.slice(b, p + 1, n)
        removed = F.slice(short, p, n + 1) == F.slice(long, p + 1, n + 1)
        return F.when(na == nb, (p == 0) | replaced).when(F.abs(na - nb) == 1, (p == 0) | removed).otherwise(False)

    return let(F.array_position(F.zip_with(short, F.slice(long, F.lit(1), F.size(short)), lambda x, y: x == y), False).cast("int"), after)


def near_copies(docs: DataFrame, firsts: DataFrame, bound: LineBound = LineBound(), text: str = "text") -> DataFrame:
    """The places among `firsts` that have an earlier near copy, each with the earliest found."""
    halves = firsts.select(*PLACE, "n", F.explode("halves").alias("half"))
    shared = halves.groupBy(F.col("half.h").alias("h")).agg(F.count("*").alias("members"), (F.min("n") != F.max("n")).alias("uneven")).where("members > 1")
    left = halves.join(shared, F.col("half.h") == F.col("h"))
    # lines of one length can only differ by a replaced word, and share the longer half; others also by a removed one
    same = F.col("half.m") == F.floor(F.col("n") / 2)
    left = left.where(same | F.col("uneven")).withColumn("half", F.struct("half.*", same.alias("same"), "uneven"))
    by_doc = left.groupBy(*PLACE).agg(F.collect_set("half").alias("halves")).groupBy("doc", "tag").agg(F.collect_list(F.struct("line_no", "halves")).alias("near"))
    texts = docs.select(F.col("doc_id").alias("doc"), F.xxhash64(text).alias("tag"), F.col(text).alias("__text")).where(F.col("__text").isNotNull())
    found = _places(texts, by_doc, "inner", ("doc", "tag"))  # repeated rows repeat their lines, which adds no pair
    lines = found.select(
        "doc", "tag", F.inline(let(F.split("__text", "\n"), lambda t: F.transform("near", lambda x: F.struct(x["line_no"].alias("line_no"), x["halves"].alias("halves"), F.get(t, x["line_no"]).alias("line")))))
    ).select(*PLACE, words_of(F.lower("line")).alias("words"), "halves")
    lines = cut(lines)
    variants = written(_variants(lines, bound), "variants")
    place, family = F.struct(*PLACE), (F.col("kind") == 2).alias("family")
    groups = variants.groupBy("key", family).agg(
        F.min(F.when(F.col("kind") != 1, place)).alias("first"), F.min(F.when(F.col("kind") == 1, place)).alias("first_cut"), F.count("*").alias("n")
    ).where("n > 1")
    partner = F.when(F.col("kind") == 0, F.col("first_cut")).otherwise(F.col("first"))
    pairs = (
        variants.withColumn("family", F.col("kind") == 2).join(groups, ["key", "family"])
        .withColumn("to", partner).where(F.col("to") < place).select(*PLACE, "to").distinct()
    )
    one = _places(pairs, lines.select(*PLACE, F.col("words").alias("a")), "inner")
    earlier = lines.select(F.struct(*PLACE).alias("to"), F.col("words").alias("b"))
    both = one.withColumnRenamed("to", "__to").join(earlier, F.equal_null(F.col("__to"), F.col("to")))
    return both.where(one_edit(F.col("a"), F.col("b"))).groupBy(*PLACE).agg(F.min("to").alias("to"))


def dedup_lines(docs: DataFrame, bound: LineBound = LineBound(), text: str = "text") -> DataFrame:
    """docs with `text` cut down to its kept lines, and n_lines and n_kept (lines with a word)."""
    firsts = cut(_first_places(docs, bound, text))
    stay = _places(firsts.drop("halves", "n"), near_copies(docs, firsts, bound, text).drop("to"), "left_anti")
    kept = stay.groupBy("doc", "tag").agg(F.collect_list("line_no").alias("__kept"))
    right = kept.select(F.col("doc").alias("__doc"), F.col("tag").alias("__tag"), "__kept")
    joined = docs.withColumn("__hash", F.xxhash64(text)).join(right, F.equal_null(F.col("doc_id"), F.col("__doc")) & (F.col("__hash") == F.col("__tag")), "left")

    def rebuilt(lines: Column) -> Column:
        blank = F.filter(F.transform(lines, lambda x, i: F.when(~x.rlike(NOT_WHITE), i)), lambda x: x.isNotNull())
        places = F.array_sort(F.concat(F.coalesce("__kept", F.array().cast("array<int>")), blank))
        return F.struct(
            F.array_join(F.transform(places, lambda i: F.get(lines, i)), "\n").alias("text"), (F.size(lines) - F.size(blank)).cast("long").alias("n"),
        )

    out = joined.withColumn("__new", F.when(F.col(text).isNotNull(), let(F.split(text, "\n"), rebuilt)))
    counts = {"n_lines": F.coalesce("__new.n", F.lit(0).cast("long")), "n_kept": F.coalesce(F.size("__kept"), F.lit(0)).cast("long")}
    return out.withColumns(counts | {text: F.col("__new.text")}).drop("__hash", "__doc", "__tag", "__kept", "__new")
