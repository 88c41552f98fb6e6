import brute
import corpus_pipeline as pipe
from graphslices.llm import line_quality, pii_surrogates
from graphslices.llm.queries import QUERIES, tokenizer_path


def test_stages_in_order():
    assert [n for n, _ in pipe.STAGES] == ["quality rules", "line dedup", "near-duplicates", "surrogates", "packing"]
    assert sorted(int(q[2:].split("_")[0]) for q in QUERIES) == list(range(1, 11))


def test_run_against_a_plain_version(spark, tmp_path):
    import random

    from tokenizers import Tokenizer

    rng = random.Random(6)
    word = lambda: "".join(rng.choice("abcdefgh") for _ in range(rng.randint(2, 6)))
    docs = {i: "\n".join(" ".join(word() for _ in range(rng.randint(9, 30))) + "." for _ in range(3)) for i in range(12)}
    docs[12], docs[13] = docs[0], docs[1].replace(docs[1].split()[3], "changed", 1)
    docs[14], docs[15], docs[16] = "too short", "a | b | c | d | e | f | g | h | i | j | k | l", None
    docs[17] = docs[2] + "\nWrite to me at first.last@mail.example.com or call +1 (424) 555-6469 on any day you like."
    df = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in docs.items()], "doc_id long, text string, lang string, source string, n_chars long")
    df.write.parquet(str(tmp_path / "documents.parquet"))
    steps, now = {}, df
    for name, stage in pipe.STAGES[:-1]:
        now = stage(spark, now, str(tmp_path)).cache()
        assert now.columns == df.columns
        steps[name] = {r.doc_id: r.text for r in now.collect()}
        assert all(r.n_chars == len(r.text) for r in now.collect())
    assert steps["quality rules"] == {i: t for i, t in docs.items() if i not in (14, 15, 16)}
    lines = brute.kept_lines(steps["quality rules"])
    assert steps["line dedup"] == {i: t for i, t in lines.items() if t}
    comp = brute.near_components(steps["line dedup"])
    assert set(steps["near-duplicates"]) == {i for i, c in comp.items() if c == i}
    assert "first.last@" not in steps["surrogates"][17] and "555-6469" not in steps["surrogates"][17]
    got = pipe.run(spark, str(tmp_path)).collect()
    t = Tokenizer.from_file(tokenizer_path())
    want = {i: len(t.encode(x, add_special_tokens=False).ids) + 1 for i, x in steps["surrogates"].items()}
    have = {}
    for r in got:
        have[r.doc_id] = have.get(r.doc_id, 0) + r.length
    assert have == want


def test_stages_on_odd_rows(spark, odd_docs, no_docs):
    for docs in (odd_docs, no_docs):
        for _, stage in pipe.STAGES[:-1]:
            out = stage(spark, docs, "")
            assert out.columns == docs.columns and out.count() <= docs.count()
        assert pipe.packing(spark, docs, "").count() >= (docs.count() > 0)
    assert line_quality.clean(no_docs).count() == pii_surrogates.with_surrogates(no_docs, "key").count() == 0


def test_near_duplicates_down_to_similarity_080(spark):
    """Pairs with two words of 104 replaced have a similarity of 90 / 110: a threshold of 0.85 leaves both copies."""
    docs = {}
    for i in range(40):
        words = [f"w{i}x{k}" for k in range(104)]
        docs[2 * i] = " ".join(words)
        words[20], words[70] = "other", "changed"
        docs[2 * i + 1] = " ".join(words)
    df = spark.createDataFrame(list(docs.items()), "doc_id long, text string")
    comp = brute.near_components(docs, 80)
    want = {i for i, c in comp.items() if c == i}
    assert len(want) == 40 and len(set(brute.near_components(docs).values())) == 80
    assert {r.doc_id for r in pipe.near_duplicates(spark, df, "").collect()} == want
