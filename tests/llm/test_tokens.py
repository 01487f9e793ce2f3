import random
import zlib
from hashlib import sha256

import numpy as np
import public_tokenizers as P
import pyarrow as pa
import pytest
import tiktoken
from lexfold.llm import bpe_codec as C
from lexfold.llm import pretokens as T
from lexfold.llm import token_store as S
from lexfold.llm.common import fresh_dir

ODD = ["", None, "a <|endoftext|> b", "<|endoftext|>", "x \n y<|endoftext|><|endoftext|>z\n\n w", " ", "  two  blanks ", "a\n b \n\n c", "tab\t tab", "it's I'LL've", "<|endoftext|> x", "  nb　 x", "naïve café ½x² ｗｉｄｅ", "😀😀 👩‍👩‍👧", "x" * 5000, "a\x1c b\x85 c", "'s 's", "\r\n \r\n"]
MULTI = P.path("byte_bpe_multi_50k.tiktoken")


def texts(spark, sf):
    return [*ODD, *(r.text for r in spark.read.parquet(f"{sf}/documents.parquet").select("text").collect())]


@pytest.mark.parametrize("name", ["byte_bpe_multi_50k.tiktoken", "byte_bpe_50k.tiktoken"])
def test_codec_equals_rank_encoder(spark, sf, name):
    ranks = C.read_ranks(P.path(name))
    right = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    codec = C.BpeCodec(ranks, P.PATTERN)
    all_texts = [t or "" for t in texts(spark, sf)]
    ids, begins = codec.encode(all_texts)
    for t, a, b in zip(all_texts, begins, begins[1:], strict=False):
        assert ids[a:b].tolist() == right.encode_ordinary(t)
        assert codec.decode(ids[a:b].tolist()) == t.encode()


def test_digests(spark, sf):
    right = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=C.read_ranks(MULTI), special_tokens={})
    rows = [(i, t, "extra") for i, t in enumerate(texts(spark, sf))] + [(None, "null id", None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, ids string").repartition(3)
    got = {r.doc_id: r for r in C.digests(df, MULTI, P.PATTERN).collect()}
    assert len(got) == len(rows)
    for i, t, _ in rows:
        ids = right.encode_ordinary(t or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i].decoded_sha256 == sha256((t or "").encode()).hexdigest()
    full = {r.doc_id: r for r in C.encode_decode(df, MULTI, P.PATTERN).collect()}
    assert all(bytes(full[i].decoded) == (t or "").encode() for i, t, _ in rows)
    assert C.digests(df.limit(0), MULTI, P.PATTERN).count() == 0


@pytest.mark.parametrize("most", [0, 2_000, 60_000, 1 << 30])
def test_cache_that_shrinks(spark, sf, most):
    own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=C.read_ranks(MULTI), special_tokens={})
    codec = C.BpeCodec(C.read_ranks(MULTI), P.PATTERN)
    codec.cached.most = most
    all_texts = [t or "" for t in texts(spark, sf)][:120]
    for _ in range(2):
        for lo in range(0, len(all_texts), 7):
            ids, begins = codec.encode(all_texts[lo : lo + 7])
            assert [ids[a:b].tolist() for a, b in zip(begins, begins[1:], strict=False)] == [own.encode_ordinary(t) for t in all_texts[lo : lo + 7]]


def test_cuts_equal_the_pattern(spark, sf):
    rng = random.Random(6)
    some = ["".join(rng.choices("stmdrevl'' \n\t aZ09.,!\u3000\x85\xa0ßé½中😀\u0301\x1c\0\u0663\U00034000", k=rng.choice([0, 1, 2, 3, 5, 9, 30]))) for _ in range(20_000)]
    own = T.CachedEncoder(P.PATTERN, None)
    assert own.by_runs
    for part in (some, [t or "" for t in texts(spark, sf)], [], ["", ""]):
        pieces, before = own._pieces(pa.array(part, pa.string()))
        got = pieces.to_pylist()
        assert [got[a:b] for a, b in zip(before, before[1:], strict=False)] == [own.cut(t) for t in part]


def test_only_pieces_are_kept_and_each_is_encoded_once(spark, sf):
    all_texts, asked = [t or "" for t in texts(spark, sf)], []

    def encode(pieces):
        asked.extend(map(str, pieces))
        return np.zeros(len(pieces), np.uint32), np.ones(len(pieces), np.int64)

    own = T.CachedEncoder(P.PATTERN, encode)
    for _ in range(2):
        for lo in range(0, len(all_texts), 50):
            own.encode(all_texts[lo : lo + 50])
    distinct = {p for t in all_texts for p in own.cut(t)}
    assert len(asked) == len(distinct)
    assert own.kept == sum(T.EACH + len(p.encode()) + 4 for p in distinct)


def test_characters_are_classed_as_the_library_has_them():
    from tokenizers import Tokenizer

    name = P.path("byte_bpe_50k.json")
    points = [*range(1, 0xD800), *range(0xE000, 0x33400), *range(0x33400, 0x110000, 997)]
    odd = [f"a{chr(c)}1 {chr(c)}!{chr(c)}" for c in points[::7] + [0x558, 0x88F, 0x1C89, 0x208F, 0xA7CE, 0x107BB]]
    ids, begins = S._encoder(name, P.PATTERN).encode(odd)
    right = Tokenizer.from_file(name).encode_batch_fast(odd, add_special_tokens=False)
    assert [ids[a:b].tolist() for a, b in zip(begins, begins[1:], strict=False)] == [x.ids for x in right]


def test_tokenizers_of_other_kinds(spark, sf):
    from tokenizers import Tokenizer

    name = P.path("word_bpe_49k.json")
    all_texts = [t or "" for t in texts(spark, sf)][:60]
    ids, begins = S._encoder(name, P.PATTERN).encode(all_texts)
    t = Tokenizer.from_file(name)
    assert [ids[a:b].tolist() for a, b in zip(begins, begins[1:], strict=False)] == [t.encode(x, add_special_tokens=False).ids for x in all_texts]


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_planes(kind):
    rng = np.random.default_rng(3)
    for n in (1, 7, 8, 1000):
        for top in (1, 2, 300, 60_000, 2**32):
            ids = rng.integers(0, top, n, dtype=np.uint32)
            assert (S.from_planes(S.to_planes(ids, kind), n, kind) == ids).all()


@pytest.mark.parametrize("kind", ["byte", "bit"])
def test_file_round_trip_over_chunks(tmp_path, kind):
    rng = np.random.default_rng(4)
    lengths = np.array([0, 5, 700, 1, 64, 64, 0, 3])
    ids = rng.integers(0, 70_000, lengths.sum(), dtype=np.uint32)
    w = S.Writer(str(tmp_path / "x.ids"), kind, chunk=64)
    w.add([9, 1, None, 4], lengths[:4], ids[: lengths[:4].sum()])
    w.add([5, 6, 7, 8], lengths[4:], ids[lengths[:4].sum() :])
    w.close()
    at = 0
    for (doc, n, parts), right, own in zip(S.Reader(str(tmp_path / "x.ids")).documents(), lengths, [9, 1, None, 4, 5, 6, 7, 8], strict=True):
        assert (doc, n) == (own, right)
        assert np.array_equal(np.concatenate([np.zeros(0, np.uint32), *parts]), ids[at : at + n])
        at += n


def test_store(spark, sf):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    assert t.encode("a <|endoftext|> b", add_special_tokens=False).ids == [64, 220, 50256, 275]
    rows = [(i * 3 - 20, x, "y") for i, x in enumerate(texts(spark, sf))]
    df = spark.createDataFrame(rows, "doc_id long, text string, start string").repartition(4)
    got = {r.doc_id: r for r in S.read_store(S.write_store(df, fresh_dir(spark, "t"), P.path("byte_bpe_50k.json"), P.PATTERN)).collect()}
    start = 0
    for d, x, _ in sorted(rows):
        ids = np.array([*t.encode(x or "", add_special_tokens=False).ids, 0], "<u4")
        assert (got[d].start, got[d].n_tokens, got[d].ids_crc32) == (start, len(ids), zlib.crc32(ids.tobytes()))
        start += len(ids)
    assert S.read_store(S.write_store(df.limit(0), fresh_dir(spark, "t"), P.path("byte_bpe_50k.json"), P.PATTERN)).count() == 0
