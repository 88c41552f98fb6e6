import zlib
from itertools import combinations

import numpy as np
import pytest

from graphslices.llm import bpe, dac, dp_packing, unigram_pieces as uni
from graphslices.llm.queries import tokenizer_path

TEXTS = ["", "  a", " a b", "a  b ", "x\ny z", "x \n y", " ", " don't  stop\t\tnow ", "é ü x", "a  b　 c   d  e à\u0085 f", "a" * 3000, "it's John.'s we're.\nwe'll!?..x.5 5.x é.\nA", "The x.\n\nThe\n\nB \nC\n D\r\nE\x0b\nF", "☃ 日本語 テキスト 😀", "\x00 a\x00b"]


@pytest.fixture(scope="module")
def path():
    return tokenizer_path()


def test_ids_are_the_librarys(path):
    from tokenizers import Tokenizer

    want = [e.ids for e in Tokenizer.from_file(path).encode_batch(TEXTS, add_special_tokens=False)]
    enc = bpe.encoder(path)
    assert [x.tolist() for x in enc.encode_many(TEXTS)] == want == [x.tolist() for x in enc.encode_many(TEXTS)]
    assert enc.encode_many([None])[0].tolist() == []
    joined = " and then ".join(TEXTS * 3)
    assert enc.encode_many([joined])[0].tolist() == Tokenizer.from_file(path).encode(joined, add_special_tokens=False).ids


def test_small_blocks_and_tables_change_nothing(path, monkeypatch):
    whole = [x.tolist() for x in bpe.encoder(path).encode_many(TEXTS)]
    enc = bpe.Encoder(path, bound=3)
    monkeypatch.setattr(bpe, "BLOCK", 40)
    assert [x.tolist() for x in enc.encode_many(TEXTS)] == whole


def letters(n):
    """A word of two letters and its complement that polynomial hashes modulo powers of two do not tell apart."""
    word = "".join("ab"[i.bit_count() & 1] for i in range(n))
    return [word, word.translate(str.maketrans("ab", "ba"))]


def test_words_that_polynomials_confuse(path):
    from tokenizers import Tokenizer

    texts = [t for n in (16, 64, 1024, 2048, 4096) for t in letters(n)] + [" ".join(letters(1024) * 2), " \x00a", " \x00a\x00", "a\x00"]
    want = [e.ids for e in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    enc = bpe.Encoder(path)
    assert [x.tolist() for x in enc.encode_many(texts)] == want == [x.tolist() for x in enc.encode_many(texts)]


def test_stretches_of_one_hash_are_told_apart(path, monkeypatch):
    from tokenizers import Tokenizer

    monkeypatch.setattr(bpe, "scramble", lambda x: x)  # a bijection under which sums of eight bytes collide
    texts = ["ABCDEFGHIJKLMNOP", "IJKLMNOPABCDEFGH", "0000000z1111111}", "aaaaaaa", "1111111}0000000z"]
    keys = [bpe.stretch_keys(np.frombuffer(t.encode(), np.uint8), np.array([0]), np.array([len(t)]))[0][0] for t in texts]
    assert len(set(keys)) == 2
    want = [e.ids for e in Tokenizer.from_file(path).encode_batch(texts, add_special_tokens=False)]
    for order in (1, -1):
        enc = bpe.Encoder(path)
        for _ in range(2):
            assert [x.tolist() for x in enc.encode_many(texts[::order])] == want[::order]
            assert [enc.encode_many([t])[0].tolist() for t in texts] == want


@pytest.mark.parametrize("n", [0, 1, 511, 512, 513, 3000])
@pytest.mark.parametrize("top", [2, 256, 60_000, 2**32 - 1])
def test_codes_give_random_access(n, top):
    rng = np.random.default_rng(n + top % 97)
    ids = rng.integers(0, top, n, dtype=np.uint32)
    r = dac.Reader(dac.pack(ids))
    assert [r[i] for i in range(n)] == ids.tolist()
    for _ in range(30):
        i, j = sorted(rng.integers(0, n + 1, 2).tolist())
        assert r.slice(i, j).tolist() == ids[i:j].tolist()
    with pytest.raises(IndexError):
        r[n]
    with pytest.raises(ValueError):
        dac.Reader(b"else")


def test_token_files(spark, odd_docs, no_docs, path, monkeypatch):
    from tokenizers import Tokenizer

    got = dac.round_trip(odd_docs, path).collect()
    assert len(got) == odd_docs.count() and dac.round_trip(no_docs, path).count() == 0
    t, at = Tokenizer.from_file(path), 0
    rows = sorted(((r.doc_id, r.text) for r in odd_docs.collect()), key=lambda x: (x[0] is not None, x[0] or 0, x[1] is not None, x[1] or ""))
    for (doc, text), r in zip(rows, sorted(got, key=lambda r: r.start), strict=True):
        ids = (t.encode(text, add_special_tokens=False).ids if text else []) + [0]
        assert (r.doc_id, r.start, r.n_tokens, r.ids_crc32) == (doc, at, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes()))
        at += len(ids)


def cost_of(chain, places, costs, p):
    total = 0
    for a, b in zip(chain, chain[1:]):
        n = int(places[b] - places[a])
        if n > p.length:
            return float("inf")
        total += (0 if n & (n - 1) == 0 or n == p.length else p.length - n) + costs[b] + p.sequence
    return total


def test_cuts_are_the_cheapest():
    rng = np.random.default_rng(5)
    for k in range(150):
        n, p = int(rng.integers(1, 10)), dp_packing.PackingCosts(length=128 if k % 2 else 100)
        places = np.concatenate([[0], np.cumsum(rng.choice([1, 2, 4, 16, 32, 64, 7, 25], n))])
        costs = rng.choice([0.0, 4.0, 24.0], n + 1)
        best = min(cost_of((0, *m, n), places, costs, p) for r in range(n) for m in combinations(range(1, n), r))
        assert abs(cost_of(dp_packing.cuts(places, costs, p), places, costs, p) - best) < 1e-9


@pytest.mark.parametrize("length,block", [(1024, 4_000_000), (64, 1000)])
def test_packing(spark, odd_docs, no_docs, path, length, block):
    costs = dp_packing.PackingCosts(length=length, block=block)
    pieces = dp_packing.pack(odd_docs, path, costs).collect()
    assert dp_packing.pack(no_docs, path, costs).count() == 0
    want = {}
    for r in dac.round_trip(odd_docs, path).collect():
        want.setdefault(r.doc_id, []).append(r.n_tokens)
    by_doc, by_seq = {}, {}
    for r in pieces:
        by_doc.setdefault(r.doc_id, []).append(r)
        by_seq.setdefault(r.sequence_id, []).append(r)
    assert {d: sum(r.length for r in rs) for d, rs in by_doc.items()} == {d: sum(n) for d, n in want.items()}
    one = sorted(by_doc[5], key=lambda r: r.start)
    assert [r.start for r in one] == np.cumsum([0] + [r.length for r in one])[:-1].tolist() and one[0].doc_tokens == sum(r.length for r in one)
    for rs in by_seq.values():
        rs.sort(key=lambda r: r.offset)
        assert [r.offset for r in rs] == np.cumsum([0] + [r.length for r in rs])[:-1].tolist() and sum(r.length for r in rs) <= length
    # all full but the last of each stretch, within a stride
    short = [n for n in (sum(r.length for r in rs) for rs in by_seq.values()) if n < length - costs.stride and n & (n - 1)]
    assert len(short) <= 8 + 40 * (block < 10_000)
    assert {r.ids_crc32 for r in by_doc[4]} == {zlib.crc32(b"\0\0\0\0")}


@pytest.fixture(scope="module")
def vocabulary():
    return uni.load_vocabulary(tokenizer_path("piece_bpe_32k.model"))


def test_double_array():
    keys = [b"a", b"ab", b"abc", b"b", b"\x00", b"\xff\xfe", b"bcd"]
    base, check, piece = uni.double_array(keys, list(range(len(keys))))

    def find(key):
        s = 0
        for c in key:
            t = base[s] + c + 1
            if t >= len(check) or check[t] != s:
                return None
            s = t
        return piece[s] if piece[s] >= 0 else None

    assert [find(k) for k in keys] == list(range(len(keys)))
    assert [find(k) for k in (b"ac", b"bc", b"abcd", b"\xff")] == [None] * 4


def test_segmentation_scores_equal_the_librarys(vocabulary):
    import sentencepiece
    from sentencepiece import sentencepiece_model_pb2 as pb

    m = pb.ModelProto()
    m.ParseFromString(open(tokenizer_path("piece_bpe_32k.model"), "rb").read())
    m.trainer_spec.model_type = 1
    for i, p in enumerate(m.pieces):
        p.score = float(vocabulary.score[i])
    lib, seg = sentencepiece.SentencePieceProcessor(model_proto=m.SerializeToString()), uni.Segmenter(vocabulary)
    for text, ids in zip(TEXTS, seg.encode_many(TEXTS), strict=True):
        want = lib.encode(text)
        assert abs(vocabulary.score[want].sum() - vocabulary.score[ids].sum()) < 1e-3, text


def test_segmentation_is_best_by_brute_force(vocabulary):
    seg = uni.Segmenter(vocabulary)
    names = {vocabulary.raw[i].decode(errors="ignore").replace(" ", "▁"): s for i, s in enumerate(vocabulary.score) if i > 258}

    def best(w):
        top = [0.0] + [-1e18] * len(w)
        for j in range(1, len(w) + 1):
            for i in range(max(0, j - 16), j):
                s = names.get(w[i:j], seg.unknown if j == i + 1 else None)
                if s is not None:
                    top[j] = max(top[j], top[i] + s)
        return top[-1]

    for w in ("▁hello", "▁internationalisation", "▁ünïcödë", "▁xqzv", "▁☃a"):
        ids = seg.segment([w.encode()])[0]
        assert abs(sum(vocabulary.score[i] for i in ids if i >= 0) + seg.unknown * len([c for c in w if not any(c in n for n in names)]) - best(w)) < 1e-6


def test_decoding_gives_every_text_back(vocabulary):
    seg = uni.Segmenter(vocabulary, bound=5)
    texts = [*TEXTS, "a▁b ▁ c", "▁", "▁▁ x"]
    for _ in range(2):
        for t, ids in zip(texts, seg.encode_many(texts), strict=True):
            assert (seg.decode(ids) if len(ids) else "") == t


def test_encoding_documents(spark, odd_docs, no_docs, vocabulary):
    got = uni.encode(odd_docs, vocabulary, with_ids=True).collect()
    assert len(got) == odd_docs.count() and all(r.round_trip for r in got) and uni.encode(no_docs, vocabulary).count() == 0
    by = {r.doc_id: r for r in got}
    assert by[3].n_pieces == by[4].n_pieces == 0 and by[6].n_byte_pieces > 0 and by[11].n_pieces > 1000
    assert all(zlib.crc32(np.array(r.ids, "<u4").tobytes()) == r.ids_crc32 and len(r.ids) == r.n_pieces for r in got)
