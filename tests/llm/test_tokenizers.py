"""Token counts, byte-level BPE and packing against their libraries, on tables and on made-up texts."""

import hashlib
import random
import zlib

import duckdb
import numpy as np
import public_tokenizers as P
import pytest
import tiktoken
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from levelwave.llm import bpe, packing, tokens

ATOMS = list(" \n\tabcdeTHEan'st01.,!é　\xa0\x1c\x85漢字😀ñ́ÀÖßΣςİ½²ʰ") + ["  ", "'ll", " the", "ing", "<|endoftext|>", "<|end", "<|startoftext|>", "\r\n"]


def made_up(seed, n=600, longest=80):
    rng = random.Random(seed)
    return ["".join(rng.choice(ATOMS) for _ in range(rng.randint(0, longest))) for _ in range(n)]


@pytest.fixture(scope="module")
def table(small):
    return [r[0] for r in duckdb.sql(f"SELECT text FROM '{small}/documents.parquet'").fetchall()]


def test_rank_queue_equals_library(table):
    coder = bpe.ByteBPE(P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN)
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=coder.ranks, special_tokens={})
    texts = table + made_up(1) + ["aab" * 5000, "x" * 3000, "ab" * 1000 + " " * 50]
    for text, ids in zip(texts, coder.encode_all(texts), strict=True):
        ids = np.frombuffer(ids, "<u4").tolist()
        assert ids == library.encode_ordinary(text), text[:80]
        assert coder.decode(ids) == text.encode()


def test_rank_queue_survives_small_caches(monkeypatch, table):
    monkeypatch.setattr(bpe, "CACHE_ENTRIES", 50)
    coder = bpe.ByteBPE(P.path("byte_bpe_50k.tiktoken"), P.PATTERN)
    library = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=coder.ranks, special_tokens={})
    for k in range(0, 60, 5):
        for text, ids in zip(table[k : k + 5], coder.encode_all(table[k : k + 5]), strict=True):
            assert np.frombuffer(ids, "<u4").tolist() == library.encode_ordinary(text)


def test_a_lower_rank_that_comes_up_goes_first():
    queue = bpe.RankQueue(10_000)
    for rank in (9_999, 64, 4_097):
        queue.push(rank, rank)
    assert queue.lowest() == 64
    assert queue.take(64) == [64]
    assert queue.lowest() == 4_097
    queue.push(3, 1)
    assert [queue.lowest(), queue.take(3)] == [3, [1]]
    queue.give_back(4_097, [])
    assert queue.take(4_097) == [4_097] and queue.take(9_999) == [9_999] and queue.lowest() == -1


def test_roundtrip_rows(spark):
    texts = [None, "", "héllo  wörld", "héllo  wörld"]
    docs = spark.createDataFrame([(None if i == 3 else i, t, b"x") for i, t in enumerate(texts)], "doc_id long, text string, ids_sha256 binary")
    got = sorted(bpe.roundtrip(docs, P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN).collect(), key=lambda r: -1 if r["doc_id"] is None else r["doc_id"])
    assert [r["doc_id"] for r in got] == [None, 0, 1, 2] and got[1]["n_tokens"] == got[2]["n_tokens"] == 0
    assert got[1]["ids_sha256"] == hashlib.sha256(b"").hexdigest()
    assert got[3]["decoded_sha256"] == got[0]["decoded_sha256"] == hashlib.sha256("héllo  wörld".encode()).hexdigest()
    assert bpe.roundtrip(docs.limit(0), P.path("byte_bpe_multi_50k.tiktoken"), P.PATTERN).isEmpty()


def test_counts_equal_library_at_any_window(table):
    library = Tokenizer.from_file(P.path("byte_bpe_50k.json"))
    for window, overlap in ((120, 30), (1000, 64), (1 << 16, 1 << 10)):
        encoder = tokens.WindowedEncoder(P.path("byte_bpe_50k.tiktoken"), P.PATTERN, {"<|endoftext|>": 50256}, window, overlap)
        for text in table[:60] + made_up(2, 300, 400) + ["x" * 1000 + " y" * 300, " " * 500 + "z"]:
            ids, windows = encoder.spliced(text)
            assert ids.tolist() == library.encode(text, add_special_tokens=False).ids, text[:60]
            assert windows == 1 or len(text) > window


def test_count_rows(spark):
    docs = spark.createDataFrame([(1, "a b"), (2, None), (None, "a b"), (3, "é" * 700)], "doc_id long, text string").withColumn("n_tokens", F.lit("clash"))
    got = {r["doc_id"]: r for r in tokens.token_counts(docs, P.path("byte_bpe_50k.tiktoken"), P.PATTERN, {"<|endoftext|>": 50256}, limit=100).collect()}
    assert (got[1]["n_bytes"], got[1]["n_tokens"], got[1]["over_limit"]) == (3, 2, False)
    assert (got[2]["n_bytes"], got[2]["n_tokens"]) == (0, 0) and got[None]["n_tokens"] == 2 and got[3]["n_bytes"] == 1400 and got[3]["over_limit"]


def test_words_equal_library(table):
    library, coder = Tokenizer.from_file(P.path("word_bpe_49k.json")), packing.WordCoder(P.path("word_bpe_49k.json"))
    texts = table + made_up(3)
    for text, ids in zip(texts, coder.encode_all(texts), strict=True):
        assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, text[:80]


def test_pieces_cover_every_id_once(spark, small):
    docs = spark.read.parquet(f"{small}/documents.parquet")
    docs = docs.unionByName(spark.createDataFrame([(900_001, None, "en", "s", 0), (900_002, "", "en", "s", 0), (None, "hello there", "en", "s", 11)], docs.schema)).repartition(3)
    pieces = packing.pack(docs, P.path("word_bpe_49k.json")).collect()
    library = Tokenizer.from_file(P.path("word_bpe_49k.json"))
    texts = {r["doc_id"]: r["text"] or "" for r in docs.collect()}
    by_doc, by_sequence = {}, {}
    for p in pieces:
        by_doc.setdefault(p["doc_id"], []).append(p)
        by_sequence.setdefault(p["sequence_id"], []).append(p)
    assert by_doc.keys() == texts.keys()
    for doc_id, own in by_doc.items():
        ids, at = library.encode(texts[doc_id], add_special_tokens=False).ids + [2], 0
        for p in sorted(own, key=lambda p: p["start"]):
            assert p["start"] == at and p["doc_tokens"] == len(ids)
            assert p["ids_crc32"] == zlib.crc32(np.array(ids[at : at + p["length"]], "<u4").tobytes())
            at += p["length"]
        assert at == len(ids)
    places = used = 0
    for own in by_sequence.values():
        at = 0
        for p in sorted(own, key=lambda p: p["offset"]):
            assert p["offset"] == at
            at += p["length"]
        assert 0 < at <= 4096
        places += at if at & (at - 1) == 0 else 4096
        used += at
    assert 1 - used / places < 0.01
    assert packing.padding(spark.createDataFrame(pieces)).first()["padding"] == pytest.approx(1 - used / places)


def test_classes_are_reciprocal():
    assert [packing.class_of(n, 4096) for n in (4096, 2049, 2048, 1366, 1365, 1, 64)] == [1, 1, 2, 2, 3, 4096, 64]
    packer = packing.HarmonicPacker(4096)
    for k in range(40):
        packer.add(k, b"\1\0\0\0" * 1300)
    full = packer.rows()
    whole = {r[0] for r in full if r[2] == 1300}
    bins = {}
    for r in full:
        bins.setdefault(r[5], []).append(r[2])
    assert all(b[:3] == [1300] * 3 and sum(b) == 4096 for b in bins.values())  # three of a kind, then what fills the gap
    assert len(whole) == 36 and len(bins) == 12 and len(full) == 36 + 13
    packer.finish()
    assert sum(r[2] for r in full + packer.rows()) == 40 * 1300


def test_packing_of_made_up_lengths():
    rng = np.random.default_rng(4)
    for capacity in (16, 4096):
        for sizes in ([], [1], [capacity], [capacity + 1], rng.integers(1, capacity * 3 // 2, 700).tolist(), rng.geometric(8 / capacity, 700).tolist()):
            packer, ids = packing.HarmonicPacker(capacity), {k: rng.integers(0, 9, n, dtype=np.uint32).astype("<u4").tobytes() for k, n in enumerate(sizes)}
            for k, x in ids.items():
                packer.add(k, x)
                assert len(packer.gaps) <= 1 and len(packer.aside) <= 1 and len(packer.open) <= 2 * int(capacity**0.5)
            packer.finish()
            rows, bins, got = packer.rows(), {}, {}
            for doc, start, n, crc, total, sequence, offset in rows:
                assert crc == zlib.crc32(ids[doc][4 * start : 4 * (start + n)]) and total == sizes[doc]
                got.setdefault(doc, []).append((start, n))
                assert bins.setdefault(sequence, 0) == offset
                bins[sequence] += n
            assert all(n == capacity or n & (n - 1) == 0 for n in bins.values())
            assert {d: sum(n for _, n in p) for d, p in got.items()} == dict(enumerate(sizes))
            # A sequence has one piece at most that goes on in the next, beside those of documents over capacity.
            assert len(rows) <= len(sizes) + 2 * len(bins) + sum(s // capacity for s in sizes)
