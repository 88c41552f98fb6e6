import math
import random
import zlib
from collections import Counter
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

import brute
import brute_mixing
from graphslices.llm import components, context_mixing as mix, hamming_join as ham, learned_partitions as ann, shingles as sh


def near_copies(rng, base, n, rate):
    out = []
    for _ in range(n):
        w = base.split()
        for i in range(len(w)):
            if rng.random() < rate:
                w[i] = f"r{rng.randint(0, 999)}"
        out.append(" ".join(w))
    return out


@pytest.mark.parametrize("block", [1024, 3])
def test_near_duplicates_against_brute_force(spark, block):
    rng = random.Random(7)
    texts = []
    for k in range(6):
        base = " ".join(f"w{rng.randint(0, 400)}" for _ in range(rng.randint(60, 200)))
        texts += near_copies(rng, base, 12, rng.choice([0.002, 0.008, 0.012, 0.016])) + [base, base.upper(), " " + base + "\n"]
    texts += ["", "  ", "a b c", "A  b\tc", "a b c d", "one two three four five", "ONE two three four five"]
    rng.shuffle(texts)
    docs = dict(enumerate(texts))
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    want = brute.near_components(docs)
    got = {r.doc_id: r for r in ham.near_components(df, ham.HammingJoin(block=block)).collect()}
    assert {i: r.component_id for i, r in got.items()} == want
    assert all(r.n_shingles == len(brute.shingles(docs[i])) and r.kept == (want[i] == i) for i, r in got.items())
    assert 1 < len(set(want.values())) < len(texts)


def test_near_duplicates_on_odd_rows(odd_docs, no_docs):
    got = ham.near_components(odd_docs).collect()
    assert len(got) == odd_docs.count() and ham.near_components(no_docs).count() == 0
    by = {r.doc_id: r for r in got if r.doc_id is not None}
    assert (by[2].component_id, by[2].kept, by[8].component_id, by[10].component_id) == (1, False, 7, 1)
    assert (by[3].n_shingles, by[3].component_id, by[3].kept) == (0, 3, True) and by[5].n_shingles == 29_996
    assert all(r.kept and r.component_id is None for r in got if r.doc_id is None)


def test_keys_hold_every_pair_within_the_distance():
    p = ham.HammingJoin()
    rng = np.random.default_rng(1)
    for _ in range(40):
        a = rng.integers(0, 2**16, (1, p.symbols))
        b = a.copy()
        places = rng.choice(p.symbols, p.distance, replace=False)
        b[0, places] ^= 1 + rng.integers(0, 1000, p.distance)
        assert set(ham.index_keys(a, p)[0]) & set(ham.index_keys(b, p)[0])
    far = rng.integers(0, 2**16, (1, p.symbols))
    assert not set(ham.index_keys(a, p)[0]) & set(ham.index_keys(far, p)[0])


def test_shingles_of_parts_equal_those_of_the_whole(monkeypatch):
    import pyarrow as pa

    text = " ".join(f"Wörd{i % 50} {i}" for i in range(400))
    whole = sh.text_sets(pa.array([text]))[0]
    monkeypatch.setattr(sh, "CHUNK", 64)
    assert (sh.text_sets(pa.array([text]))[0] == whole).all() and len(whole) == len(brute.shingles(text))


def test_words_that_polynomials_confuse():
    for n in (64, 1024, 4096):
        word = "".join("ab"[i.bit_count() & 1] for i in range(n))
        other = word.translate(str.maketrans("ab", "ba"))
        assert len({int(sh.word_hashes(np.frombuffer(w.encode(), np.uint8))[1][0]) for w in (word, other, word[:-1], word + "\x00")}) == 4


def test_components(spark):
    rng = random.Random(3)
    links = [(rng.randint(0, 60), rng.randint(0, 60)) for _ in range(40)] + [(i, i + 1) for i in range(100, 130)] + [(200, i) for i in range(201, 230)]
    root = {}

    def find(i):
        root.setdefault(i, i)
        while root[i] != i:
            i = root[i]
        return i

    for a, b in links:
        x, y = find(a), find(b)
        root[max(x, y)] = min(x, y)
    want = {i: find(i) for a, b in links if a != b for i in (a, b)}
    got = {r.node: r.component for r in components.components(spark.createDataFrame(links, "u long, v long")).collect()}
    assert got == want
    assert components.components(spark.createDataFrame([], "u long, v long")).count() == 0


def vectors(spark, rows):
    return spark.createDataFrame(rows, "vec_id long, embedding array<float>, label int")


def test_search_recall_and_scores(spark):
    rng = np.random.default_rng(8)
    centres = rng.normal(size=(12, 24))
    x = (centres[rng.integers(0, 12, 3000)] + 0.4 * rng.normal(size=(3000, 24))).astype(np.float32)
    df = vectors(spark, [(i, v.tolist(), 0) for i, v in enumerate(x)])
    p = ann.PartitionSearch(rows_a_part=40, sample=1500, rows_block=256, query_block=32)
    by = {}
    for r in ann.search(df, F.col("vec_id") % 20 == 0, p).collect():
        by.setdefault(r.query_id, []).append(r)
    assert len(by) == 150
    hit = 0
    for q, rows in by.items():
        rows.sort(key=lambda r: r.rank)
        exact = x.astype(float) @ x[q].astype(float)
        assert [r.rank for r in rows] == list(range(1, 21)) and all(abs(r.score - exact[r.vec_id]) < 1e-9 for r in rows) and q not in [r.vec_id for r in rows]
        exact[q] = -np.inf
        hit += len({r.vec_id for r in rows} & set(np.argsort(-exact)[:20].tolist()))
    assert hit / 3000 >= 0.9
    read = [rows[0].rows_read for rows in by.values()]
    assert np.mean(read) < 0.3 * 3000 and min(read) >= 20


def test_search_of_noise_reads_a_minority(spark):
    """Vectors without any structure, as in the given tables: recall of 0.9 from less than half of the rows."""
    df = spark.read.parquet("/root/testdata/sf0.1/embeddings.parquet")
    rows = ann.search(df, F.col("vec_id") % 20 == 0).collect()
    x = {r.vec_id: np.array(r.embedding, float) for r in df.collect()}
    ids, m = np.array(list(x)), np.stack(list(x.values()))
    by = {}
    for r in rows:
        by.setdefault(r.query_id, []).append(r)
    hit = 0
    for q, found in by.items():
        exact = m @ x[q]
        exact[ids == q] = -np.inf
        hit += len({r.vec_id for r in found} & set(ids[np.argsort(-exact)[:20]].tolist()))
    assert len(by) == 100 and hit / 2000 >= 0.9 and np.mean([found[0].rows_read for found in by.values()]) < 0.5 * len(ids)


def test_balanced_parts():
    rng = np.random.default_rng(2)
    x = rng.normal(size=(512, 8))
    part = ann.balanced_parts(x, ann.neighbour_graph(x, 8), 8)
    assert np.bincount(part, minlength=8).max() <= 77
    near, random_part = ann.neighbour_graph(x, 8), rng.integers(0, 8, 512)
    kept = lambda p: (p[near] == p[:, None]).mean()
    assert kept(part) > 2 * kept(random_part)


def test_fit_holds_little_on_the_driver():
    import tracemalloc

    x = np.random.default_rng(4).normal(size=(6000, 16))
    tracemalloc.start()
    ann.fit(x, 750, ann.PartitionSearch(epochs=1))
    most = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert most < 100 << 20  # blocks of a thousand and more rows took over 200 MB


def test_search_on_odd_rows(spark):
    ok = [(i, [1.0, 0.0, 0.5], 1) for i in range(30)] + [(100 + i, [float(i), 1.0, -1.0], 1) for i in range(5)]
    odd = [(200, None, 1), (220, [], 1), (240, [0.0, 0.0, 0.0], 1), (260, [float("nan"), 1.0, 1.0], 1), (280, [float("inf"), 1.0, 1.0], 1), (300, [None, 1.0, 1.0], 1), (320, [1.0, 2.0], 1), (None, [1.0, 1.0, 1.0], 1)]
    df = vectors(spark, ok + odd).withColumns({c: F.lit("own") for c in ("v", "part", "rank", "score", "query_id")})
    by = {}
    for r in ann.search(df, F.col("vec_id") % 20 == 0, ann.PartitionSearch(rows_block=7, query_block=2)).collect():
        by.setdefault(r.query_id, []).append((r.rank, r.vec_id))
    assert set(by) == {0, 20, 100}
    # vectors 101 to 104 score less or more than the equal ones; ties go to the smaller id, whatever block they lie in
    score = {i: np.dot(v, [1.0, 0.0, 0.5]) for i, v, _ in ok}
    want = sorted((i for i in score if i != 0), key=lambda i: (-score[i], i))[:20]
    assert [v for _, v in sorted(by[0])] == want
    few = ann.search(df.where("vec_id < 5 OR vec_id = 240"), F.col("vec_id") % 20 == 0).collect()
    assert sorted(r.vec_id for r in few) == [1, 2, 3, 4]
    assert ann.search(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0
    assert ann.search(df.where("vec_id = 0"), F.col("vec_id") % 20 == 0).count() == 0


def zipf_docs(rng, n):
    vocabulary = [f"{a}{b}" for a in ("ka", "lo", "mi", "nu", "re", "so", "ti") for b in ("ba", "den", "fir", "gol", "hus", "jam", "")]
    docs = []
    for i in range(n):
        w, last = [], 0
        for _ in range(rng.randint(5, 120)):
            last = (last * 3 + int(rng.expovariate(0.3))) % len(vocabulary) if rng.random() < 0.8 else rng.randrange(len(vocabulary))
            w.append(vocabulary[last] + rng.choice(["", "", "", "."]))
        docs.append((i, " ".join(w)))
    return docs


def test_base_score_is_exact_and_context_helps(spark):
    docs = zipf_docs(random.Random(5), 900) + [(5000, None), (5001, ""), (5002, "NeverSeen word ☃")]
    df = spark.createDataFrame(docs, "doc_id long, text string")
    c = Counter()
    tokens = {i: brute.words(brute.lower(t)) + [None] for i, t in docs}
    held = {i: zlib.crc32(str(i).encode()) % 7 == 2 for i in tokens}
    for i, w in tokens.items():
        if not held[i]:
            c.update(w)
    n, v = sum(c.values()), len(c)
    rows = mix.score(df).collect()
    assert len(rows) == len(docs)
    base = own = 0
    text = dict(docs)
    for r in rows:
        w = tokens[r.doc_id]
        want = sum(math.log10((c[x] + 1) / (n + v + 1)) for x in w)
        assert abs(r.base_score - want) < 1e-6 and (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[r.doc_id], len(w), sum(x in c for x in w), n)
        assert math.isfinite(r.score) and r.score < 0 and r.n_bytes == len((text[r.doc_id] or "").encode())
        assert abs(r.bits + r.score * math.log2(10)) < 1e-6 and (r.bits_per_byte is None if not r.n_bytes else abs(r.bits_per_byte * r.n_bytes - r.bits) < 1e-6)
        if r.held_out:
            base, own = base + r.base_score, own + r.score
    assert own > base + 0.1 * abs(base)


def copied_docs(rng, n):
    words = [f"w{i}" for i in range(30)] + ["ünï", "x" * 70]
    plain = [" ".join(rng.choice(words) for _ in range(rng.randint(0, 40))) for _ in range(n)]
    plain += [rng.choice(plain) + rng.choice(["", " tail", f" rare{i} End"]) for i in range(n)]
    return [(i, t) for i, t in enumerate(plain)]


@pytest.mark.parametrize("anchor", [1, 4])
def test_scores_equal_a_plain_mixer(spark, anchor):
    docs = copied_docs(random.Random(anchor), 40)
    p = mix.MixingModel(kind="f8", anchor=anchor, first=8, longest=16, table_bits=11, byte_bits=10, share=9, levels=5, batch=7)
    want = brute_mixing.scores(docs, p)
    for parts in (1, 5):  # however the rows are dealt
        got = {r.doc_id: r.score for r in mix.score(spark.createDataFrame(docs, "doc_id long, text string").repartition(parts), p).collect()}
        assert all(abs(got[i] - want[i]) < 1e-9 * max(1, abs(want[i])) for i in want)


def test_probabilities_of_all_texts_add_up_to_one_at_most(spark):
    rng = random.Random(2)
    held = [i for i in range(20_000) if zlib.crc32(str(i).encode()) % 7 == 2]
    other = [i for i in range(2000) if zlib.crc32(str(i).encode()) % 7 != 2]
    train = [(i, " ".join(rng.choice("abc") for _ in range(rng.choice([0, 1, 2, 3, 5, 6])))) for i in other[:800]]
    every = [" ".join(t) for k in range(7) for t in product("abc", repeat=k)]
    asked = list(zip(held, every))
    rows = {r.doc_id: r for r in mix.score(spark.createDataFrame(train + asked, "doc_id long, text string"), mix.MixingModel(anchor=2, first=2)).collect()}
    by_length = Counter()
    for i, t in asked:
        assert rows[i].held_out
        by_length[len(t.split())] += 10 ** rows[i].score
    assert 0.75 < sum(by_length.values()) <= 1 + 1e-6
    share = Counter(len(t.split()) for _, t in train)
    assert all(abs(by_length[k] - share[k] / 800) < 0.08 for k in (0, 1, 2, 3))  # ends are told by what precedes them


def test_what_is_met_twice_scores_better(spark):
    rng = random.Random(9)
    once = [(i, " ".join(f"k{rng.randint(0, 300)}" for _ in range(150))) for i in range(200)]
    twice = [(1000 + i, t) for i, (_, t) in enumerate(once[:40])]
    rows = {r.doc_id: r.score / r.n_tokens for r in mix.score(spark.createDataFrame(once + twice, "doc_id long, text string")).collect()}
    learned = lambda i: zlib.crc32(str(i).encode()) % 7 != 2
    double = [rows[i] for i in range(40) if learned(i) and learned(1000 + i)]
    assert min(double) > max(v for i, v in rows.items() if 40 <= i < 200)


def test_scoring_odd_rows(odd_docs, no_docs):
    got = mix.score(odd_docs).collect()
    assert len(got) == odd_docs.count() and mix.score(no_docs).count() == 0
    by = {r.doc_id: r for r in got if r.doc_id}
    assert by[3].n_tokens == by[4].n_tokens == by[6].n_tokens == 1 and by[5].n_tokens == 30_001
    assert all(r.held_out for r in got if r.doc_id is None)
    only = mix.score(odd_docs.where("doc_id IS NULL")).collect()
    assert {r.train_tokens for r in only} == {0} and all(r.n_known == 0 for r in only)
