import random

import pytest
from pyspark.sql import functions as F

import brute
from graphslices.llm import line_dedup, line_quality, oracles


def rows(df, *cols):
    return sorted(map(repr, (tuple(r[c] for c in cols) for r in df.collect())))


def test_quality_on_odd_rows(odd_docs, no_docs):
    got = line_quality.measures(odd_docs)
    assert got.count() == odd_docs.count() and line_quality.measures(no_docs).count() == 0
    by = {r.doc_id: r for r in got.collect() if r.doc_id}
    assert (by[3].n_words, by[3].kept) == (0, False) and (by[4].n_words, by[4].base_failed) == (0, True) and by[6].n_words == 0
    assert by[5].n_words == 30_000 and by[5].n_repeat_words == 0 and by[1].kept and by[1].lang == "kept as it is"
    clean = line_quality.clean(odd_docs)
    assert clean.columns == odd_docs.columns and line_quality.clean(no_docs).count() == 0
    assert {r.doc_id for r in clean.collect()} >= {1, 2, 10}


def test_quality_measures_against_plain_code(spark):
    rng = random.Random(4)
    texts = ["\n".join(" ".join(rng.choice("ab cd ef # $| xy".split()) for _ in range(rng.randint(0, 9))) for _ in range(rng.randint(0, 6))) for _ in range(60)]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    for r in line_quality.measures(df).collect():
        t, w = texts[r.doc_id], brute.words(texts[r.doc_id])
        win = [tuple(w[i : i + 5]) for i in range(len(w) - 4)]
        covered = {i + k for i, x in enumerate(win) if win.count(x) > 1 for k in range(5)}
        lines = [x for x in t.split("\n") if brute.words(x)]
        assert (r.n_words, r.word_chars, r.n_symbols) == (len(w), sum(map(len, w)), sum(c in "#*$%&|<>" for c in t))
        assert (r.n_dup_lines, r.n_repeat_words) == (len(lines) - len(set(lines)), len(covered))
        assert r.base_failed == (len(w) < 10 or 100 * len(covered) > 20 * len(w))


@pytest.mark.parametrize(
    "line,fails",
    [
        ("A plain sentence of several words, with a point at its end.", False), ("Home | News | Sports | About", True), ("A%%% b### c*** d&&& e$$$ f%%%", True), ("LOUD!! WORDS!! ALL!! DAY!!", True),
        ("Sign in", True), ("All rights reserved.", True), ("", False), ("   ", False), ("Who goes there?", False), ("Menü", True), ("S'inscrire", True), ("Todos los derechos reservados.", True), ("1 2 3 4 5 6 7 8 9 10", True), ("12.05.2021", False), ("Es waren 12 Menüs da.", False), (" ".join(["word"] * 50), True),
    ],
)
def test_line_rules(spark, line, fails):
    assert spark.createDataFrame([(line,)], "x string").select(line_quality.line_fails(F.col("x")).alias("f")).first().f is fails


def test_a_document_that_loses_too_much_goes(spark):
    good, bad = "This line is prose and stays where it is in the text.", "a | b | c | d | e | f | g | h | i | j | k | l | m | n"
    df = spark.createDataFrame([(1, f"{good}\n{bad}"), (2, f"{good}\n" + f"{bad}\n" * 4)], "doc_id long, text string")
    got = {r.doc_id: r.text for r in line_quality.clean(df).collect()}
    assert got == {1: good}


def test_dedup_on_odd_rows(odd_docs, no_docs):
    got = line_dedup.dedup_lines(odd_docs)
    assert got.count() == odd_docs.count() and line_dedup.dedup_lines(no_docs).count() == 0
    assert set(odd_docs.columns) <= set(got.columns)
    null_first = [r for r in got.collect() if r.doc_id is None and r.text]
    assert len(null_first) == 1 and null_first[0].n_lines == 1
    by = {}
    for r in got.collect():
        by.setdefault(r.doc_id, []).append(r.text)
    assert by[1] == ["", ""] and by[3] == [None] and by[4] == [""] and by[6] == [" \t\n\x0b "]
    assert by[7] != by[8] and len(by[5][0]) > 100_000


def test_dedup_against_plain_code(spark):
    rng = random.Random(9)
    base = [[rng.choice("abcdefgh") + str(rng.randint(0, 3)) for _ in range(rng.randint(6, 14))] for _ in range(12)]

    def edited():
        w = list(rng.choice(base))
        for _ in range(rng.randint(0, 2)):
            i = rng.randrange(len(w))
            w[i : i + rng.randint(0, 1)] = [rng.choice("xyz")] * rng.randint(0, 1)
        return " ".join(w)

    docs = {i: "\n".join(edited() if rng.random() < 0.9 else "" for _ in range(rng.randint(1, 6))) for i in range(60)}
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    want = brute.kept_lines(docs)
    assert {r.doc_id: r.text for r in line_dedup.dedup_lines(df).collect()} == want
    long = line_dedup.dedup_lines(df, line_dedup.LineBound(ordered_words=3))  # hashes by sums over blocks
    assert {r.doc_id: r.text for r in long.collect()} == want


@pytest.mark.parametrize("words", [30, 4100])
def test_long_lines_among_their_permutations(spark, words):
    """Earlier lines of the same words in another order hide no link."""
    rng = random.Random(words)
    line = [f"w{i}" for i in range(words)]
    docs = {}
    for half in (0, 1):
        for i in range(5):
            part = line[words // 2 :] if half else line[: words // 2]
            rng.shuffle(part)
            docs[len(docs)] = " ".join(line[: words // 2] + part if half else part + line[words // 2 :])
    docs[len(docs)] = " ".join(line)
    for change in ([], ["x"]):
        for at in (0, 7, words // 2, words - 1):
            docs[len(docs)] = " ".join(line[:at] + change + line[at + 1 :])
    docs[len(docs)] = " ".join(line[:9] + ["y"] + line[9:])
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    bound = line_dedup.LineBound(ordered_words=3) if words < 100 else line_dedup.LineBound()
    got = {r.doc_id: r.text for r in line_dedup.dedup_lines(df, bound).collect()}
    assert sorted(i for i, t in got.items() if t) == list(range(11)) and got == brute.kept_lines(docs)


@pytest.mark.parametrize("a,b", [("a b c", "a b c"), ("a b c", "a x c"), ("a b c", "a b"), ("a b c", "b c"), ("a b c", "a c"), ("a b c", "c b a"), ("a b c", "a"), ("a b", "a b c d"), ("x a b", "a b y")])
def test_one_edit(spark, a, b):
    got = spark.createDataFrame([(a.split(), b.split())], "a array<string>, b array<string>").select(line_dedup.one_edit(F.col("a"), F.col("b")).alias("r")).first().r
    assert got == brute.one_edit(a.split(), b.split())


def test_sql_forms_exist():
    assert "op8_line_dedup" in oracles.ORACLES and "op9_line_quality" in oracles.ORACLES
