"""Byte-level BPE over a rank queue: one bucket of positions for each merge rank, under a bitmap of three levels.

All pre-tokens of a batch lie in one doubly linked list of symbols, cut at their ends. A pair of neighbours waits in the
bucket of its merge rank; a find-first-set through the three levels gives the lowest rank that has pairs, however many
ranks there are. A merge leaves the entries of its old neighbours behind; they are skipped when met, because the rank
noted at their place has changed. Work is linear in bytes, so a pre-token of megabytes costs as much a byte as a word.
"""

from __future__ import annotations

import base64
import hashlib
from collections.abc import Iterable, Iterator
from itertools import chain

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import documents, importable
from .textkernel import slices

QUERY = "op9_byte_bpe_roundtrip"
#: Texts remembered by a worker at most, with their ids, and characters of one that is remembered.
CACHE_ENTRIES, CACHE_LETTERS = 500_000, 256
#: Pairs of symbols whose rank (or lack of one) is remembered.
PAIR_ENTRIES = 1_000_000
SCHEMA = "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string"

#: White space right of which another one follows; only there are a space and what stands before it not separable.
_DOUBLE = regex.compile(r"\s ")
_UNIT = regex.compile(r"\s*\S+|\s+\Z")


def _fresh(lists: list[list], cache: dict) -> list:
    """What is in the lists and not in the cache, which is emptied first if it would grow too large."""
    there = set(chain.from_iterable(lists))
    fresh = [x for x in there if x not in cache]
    if len(cache) + len(fresh) > CACHE_ENTRIES:
        cache.clear()
        return list(there)
    return fresh


class RankQueue:
    """Positions by rank; the lowest rank that has any is found by three find-first-sets."""

    def __init__(self, ranks: int):
        self.buckets: list[list[int]] = [[] for _ in range(ranks)]
        self.leaf, self.mid, self.top = [0] * ((ranks >> 6) + 1), [0] * ((ranks >> 12) + 1), 0

    def push(self, rank: int, place: int) -> None:
        bucket = self.buckets[rank]
        if not bucket:
            self._mark(rank)
        bucket.append(place)

    def _mark(self, rank: int) -> None:
        self.leaf[rank >> 6] |= 1 << (rank & 63)
        self.mid[rank >> 12] |= 1 << (rank >> 6 & 63)
        self.top |= 1 << (rank >> 12)

    def lowest(self) -> int:
        """-1 if all buckets are empty."""
        if not self.top:
            return -1
        a = (self.top & -self.top).bit_length() - 1
        m = self.mid[a]
        b = a << 6 | (m & -m).bit_length() - 1
        x = self.leaf[b]
        return b << 6 | (x & -x).bit_length() - 1

    def take(self, rank: int) -> list[int]:
        """The bucket of this rank, in order of place; it is empty afterwards."""
        bucket, self.buckets[rank] = self.buckets[rank], []
        self.leaf[rank >> 6] &= ~(1 << (rank & 63))
        if not self.leaf[rank >> 6]:
            self.mid[rank >> 12] &= ~(1 << (rank >> 6 & 63))
            if not self.mid[rank >> 12]:
                self.top &= ~(1 << (rank >> 12))
        bucket.sort()
        return bucket

    def give_back(self, rank: int, places: list[int]) -> None:
        if places:
            self._mark(rank)
            self.buckets[rank] = places + self.buckets[rank]


class ByteBPE:
    """Encoder and decoder for a file of ranks (base64 token, blank, rank a line) and a pattern of pre-tokens."""

    def __init__(self, path: str, pattern: str):
        with open(path, "rb") as lines:
            self.ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
        self.vocab = [b""] * (max(self.ranks.values()) + 1)
        for token, rank in self.ranks.items():
            self.vocab[rank] = token
        self.single = np.array([self.ranks[bytes([b])] for b in range(256)])
        self.rank_of_two = np.full(1 << 16, -1, dtype=np.int64)
        for token, rank in self.ranks.items():
            if len(token) == 2:
                self.rank_of_two[token[0] << 8 | token[1]] = rank
        self.pairs: dict[int, int] = {}
        self.pattern = regex.compile(pattern)
        self.queue = RankQueue(len(self.vocab))
        self.words: dict[bytes, bytes] = {}
        self.after_space: dict[str, bytes] = {}

    def merge(self, pretokens: list[bytes]) -> list[list[int]]:
        """The ids of each pre-token, all merged through one queue."""
        whole = b"".join(pretokens)
        n = len(whole)
        if not n:
            return [[] for _ in pretokens]
        queue, vocab, ranks, pairs = self.queue, self.vocab, self.ranks, self.pairs
        data = np.frombuffer(whole, dtype=np.uint8)
        ends = np.cumsum([len(p) for p in pretokens])
        last = ends[ends > 0] - 1
        begin = np.unique(np.concatenate(([0], last[:-1] + 1)))
        first_ranks = np.full(n, -1, dtype=np.int64)
        first_ranks[:-1] = self.rank_of_two[data[:-1].astype(np.int64) << 8 | data[1:]]
        first_ranks[last] = -1
        waiting = np.flatnonzero(first_ranks >= 0)
        waiting = waiting[np.argsort(first_ranks[waiting], kind="stable")]
        edges = np.flatnonzero(np.diff(first_ranks[waiting])) + 1
        for group in np.split(waiting, edges) if len(waiting) else []:
            queue.give_back(int(first_ranks[group[0]]), group.tolist())
        noted = first_ranks.tolist()
        symbol = self.single[data].tolist()
        left, right = np.arange(-1, n - 1), np.arange(1, n + 1)
        left[begin], right[last] = -1, -1
        left, right = left.tolist(), right.tolist()
        push = queue.push
        while (rank := queue.lowest()) >= 0:
            places, shifted = queue.take(rank), rank << 16
            for k, i in enumerate(places):
                if noted[i] != rank:
                    continue  # stale
                gone = right[i]
                after, before, low = right[gone], left[i], rank
                symbol[i], symbol[gone], noted[gone] = rank, -1, -1
                right[i] = after
                if after >= 0:
                    left[after] = i
                    pair = shifted | symbol[after]
                    new = pairs.get(pair)
                    if new is None:
                        new = pairs[pair] = ranks.get(vocab[rank] + vocab[symbol[after]], -1)
                    noted[i] = new
                    if new >= 0:
                        push(new, i)
                        if new < low:
                            low = new
                else:
                    noted[i] = -1
                if before >= 0:
                    pair = symbol[before] << 16 | rank
                    new = pairs.get(pair)
                    if new is None:
                        new = pairs[pair] = ranks.get(vocab[symbol[before]] + vocab[rank], -1)
                    noted[before] = new
                    if new >= 0:
                        push(new, before)
                        if new < low:
                            low = new
                if low < rank:  # a pair of a lower rank has come up: it goes first
                    queue.give_back(rank, places[k + 1 :])
                    break
        if len(pairs) > PAIR_ENTRIES:
            pairs.clear()
        symbols = np.array(symbol, dtype=np.int64)
        live = symbols >= 0
        cuts = np.concatenate(([0], np.cumsum(live)))[np.concatenate(([0], ends))].tolist()
        ids = symbols[live].tolist()
        return [ids[a:b] for a, b in zip(cuts[:-1], cuts[1:], strict=True)]

    def _units(self, units: Iterable[str]) -> list[bytes]:
        """The ids of each unit as little-endian 32-bit integers. A unit begins after and ends before a pre-token's end."""
        split = [[p.encode() for p in self.pattern.findall(u)] for u in units]
        fresh = _fresh(split, self.words)
        whole = [p for p in fresh if p in self.ranks]
        self.words.update((p, self.ranks[p].to_bytes(4, "little")) for p in whole)
        rest = [p for p in fresh if p not in self.ranks]
        for token, ids in zip(rest, self.merge(rest), strict=True):
            self.words[token] = np.array(ids, dtype="<u4").tobytes()
        word = self.words.__getitem__
        return [b"".join(map(word, parts)) for parts in split]

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian 32-bit integers.

        Where one space follows anything but white space, a pre-token ends, whatever the rest of the text; so texts are
        cut there, and what lies between is looked up, or encoded once for the batch. Other texts are cut by a pattern.
        """
        cache, parted, odd = self.after_space, [], {}
        for k, text in enumerate(texts):
            if _DOUBLE.search(text):
                odd[k] = _UNIT.findall(text)
                parted.append([])
            else:
                parted.append(text.split(" "))
        heads = self._units([parts[0] if parts else "" for parts in parted])
        parted = [parts[1:] for parts in parted]
        new = _fresh(parted, cache)
        cache.update(zip(new, self._units([" " + p for p in new]), strict=True))
        loose = {k: self._units(units) for k, units in odd.items()}
        known = cache.__getitem__
        out = [b"".join(loose[k]) if k in loose else head + b"".join(map(known, parts))
               for k, (head, parts) in enumerate(zip(heads, parted, strict=True))]
        for long in [p for p in new if len(p) > CACHE_LETTERS]:
            del cache[long]
        return out

    def encode(self, text: str) -> list[int]:
        return np.frombuffer(self.encode_all([text])[0], dtype="<u4").tolist()

    def decode(self, ids: Iterable[int]) -> bytes:
        return b"".join(map(self.vocab.__getitem__, ids))


_coders: dict[tuple[str, str], ByteBPE] = {}


def coder(path: str, pattern: str) -> ByteBPE:
    """One for each worker process, which keeps it between tasks."""
    if (path, pattern) not in _coders:
        _coders[path, pattern] = ByteBPE(path, pattern)
    return _coders[path, pattern]


def encode_documents(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """(doc_id, ids): the ids of each whole text; a null text is empty and has no ids. Repeated rows stay repeated."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path, pattern)
        for part in slices(batches):
            packed = bpe.encode_all([t or "" for t in part.column(1).to_pylist()])
            ids = [np.frombuffer(x, dtype="<u4").astype(np.int32) for x in packed]
            yield pa.RecordBatch.from_arrays([part.column(0), pa.array(ids, pa.list_(pa.int32()))], ["doc_id", "ids"])

    importable(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, "doc_id long, ids array<int>")


def roundtrip(docs: DataFrame, path: str, pattern: str) -> DataFrame:
    """Encodes each whole text, decodes the ids again, and returns digests of both.

    Null and empty texts have no ids, and the digests of nothing. Rows come out as often as they come in; null ids stay
    null; other columns aren't read. Texts are taken in slices of about 2 MB, a longer text by itself.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        bpe = coder(path, pattern)
        sha = hashlib.sha256
        for part in slices(batches):
            packed = bpe.encode_all([t or "" for t in part.column(1).to_pylist()])
            back = [sha(bpe.decode(np.frombuffer(x, dtype="<u4").tolist())).hexdigest() for x in packed]
            yield pa.RecordBatch.from_arrays(
                [part.column(0), pa.array([len(x) // 4 for x in packed], pa.int64()), pa.array([sha(x).hexdigest() for x in packed]), pa.array(back)],
                ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256"])

    importable(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, SCHEMA)


def op9(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return roundtrip(documents(spark, sf_dir), public_tokenizers.path("byte_bpe_multi_50k.tiktoken"), public_tokenizers.PATTERN)
