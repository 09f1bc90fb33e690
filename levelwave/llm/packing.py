"""Harmonic packing of documents into training sequences, each worker for itself and in one pass without a shuffle.

Lengths fall into reciprocal classes: class i holds documents of more than capacity / (i + 1) and at most capacity / i ids,
whole, and each of its bins takes exactly i of them. As documents may be cut, the gap that a full bin leaves isn't padded:
it takes the next ids of a document set aside for gaps, the end of one longer than capacity where there is one. So a
document is whole unless it is longer than capacity or fills gaps. What waits in unfilled bins when a worker's rows end is
laid end to end, cut at capacity, and its rest is cut at powers of two, which need no padding.
"""

from __future__ import annotations

import re
import struct
import zlib
from collections.abc import Iterator
from itertools import chain

import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import documents, importable
from .textkernel import slices

QUERY = "op4_harmonic_packing"
CAPACITY, END_ID = 4096, 2
#: Words remembered by a worker at most, with their ids, and characters of one that is remembered.
CACHE_ENTRIES, CACHE_LETTERS = 500_000, 256
SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"

#: Letters that lower-casing and composition leave as one letter each, then marks that are no letters.
_PLAIN = re.compile(r"([A-Za-zÀ-ÖØ-öø-ÿ]+)([.,!?;:]*)")
#: What str.split() takes for white space and the tokenizer does not.
_SEPARATORS = re.compile(r"[\x1c-\x1f]")
_SPLIT = re.compile(r"[^\S\x1c-\x1f]+")


def _little(ids: list[int]) -> bytes:
    return struct.pack(f"<{len(ids)}I", *ids)


def byte_letters() -> list[str]:
    """The printable letter that stands for each byte in byte-level vocabularies: itself where it is visible, else the
    next one from 256 on."""
    visible = {*range(0x21, 0x7F), *range(0xA1, 0xAD), *range(0xAE, 0x100)}
    out, spare = [], 0x100
    for b in range(256):
        out.append(chr(b) if b in visible else chr(spare))
        spare += b not in visible
    return out


class WordCoder:
    """Ids of texts by a vocabulary that lower-cases, drops white space and never joins across it.

    White space separates for good, so each word between is encoded by the library once and remembered. A plain word of
    letters goes straight to the library's merge model, all others through its whole chain.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.model = self.library.model
        self.letters = byte_letters()
        self.cache: dict[str, bytes] = {}
        self.stems: dict[str, bytes] = {}

    def _stem(self, stem: str) -> bytes:
        got = self.stems.get(stem)
        if got is None:
            mapped = stem if stem.isascii() else "".join([self.letters[b] for b in stem.encode()])  # ASCII letters stand for themselves
            got = self.stems[stem] = _little([t.id for t in self.model.tokenize(mapped)])
        return got

    def _whole(self, words: list[str]) -> list[bytes]:
        return [_little(e.ids) for e in self.library.encode_batch(words, add_special_tokens=False)]

    def encode_all(self, texts: list[str]) -> list[bytes]:
        """The ids of each text as little-endian 32-bit integers."""
        parted = [_SPLIT.split(t) if _SEPARATORS.search(t) else t.split() for t in texts]
        cache, there = self.cache, set(chain.from_iterable(parted))
        new = [w for w in there if w not in cache]
        if len(cache) + len(new) > CACHE_ENTRIES:
            cache.clear()
            new = list(there)
        if len(self.stems) > CACHE_ENTRIES:
            self.stems.clear()
        odd, marks = [], {}
        known = self.stems.get
        for word in new:
            if word.isascii() and word.isalpha():
                stem = word.lower()
                cache[word] = known(stem) or self._stem(stem)
                continue
            m = _PLAIN.fullmatch(word)
            if m is None:
                odd.append(word)
            elif m[2]:
                if m[2] not in marks:
                    marks[m[2]] = self._whole([m[2]])[0]
                cache[word] = self._stem(m[1].lower()) + marks[m[2]]
            else:
                cache[word] = self._stem(m[1].lower())
        cache.update(zip(odd, self._whole(odd), strict=True))
        out = [b"".join(map(cache.__getitem__, parts)) for parts in parted]
        if long := [w for w in new if len(w) > CACHE_LETTERS]:
            for word in long:
                del cache[word]
            self.stems = {s: ids for s, ids in self.stems.items() if len(s) <= CACHE_LETTERS}
        return out


def class_of(length: int, capacity: int = CAPACITY) -> int:
    """How many documents a bin of this length's class takes: the i for which it lies in (capacity / (i + 1), capacity / i]."""
    return capacity // length


class HarmonicPacker:
    """Packs what it is given, in order, into sequences numbered from first_id; rows() hands out what is settled.

    Waiting are at most a bin of each class, one set of ids for gaps, and full bins only until the next document comes.
    """

    def __init__(self, capacity: int = CAPACITY, first_id: int = 0):
        self.capacity, self.next_id = capacity, first_id
        self.open: dict[int, list[tuple]] = {}
        self.gaps: list[tuple[list[tuple], int]] = []
        self.aside: list[tuple] = []
        self.done: list[tuple] = []

    def _close(self, pieces: list[tuple]) -> None:
        offset = 0
        for doc_id, start, ids, total in pieces:
            n = len(ids) // 4
            self.done.append((doc_id, start, n, zlib.crc32(ids), total, self.next_id, offset))
            offset += n
        self.next_id += 1

    def add(self, doc_id: int | None, ids: bytes) -> None:
        """ids: little-endian 32-bit integers."""
        total, start, size = len(ids) // 4, 0, 4 * self.capacity
        while total - start >= self.capacity:
            self._close([(doc_id, start, ids[4 * start : 4 * start + size], total)])
            start += self.capacity
        if start == total:
            return
        rest = (doc_id, start, ids[4 * start :], total)
        if self.gaps or (start and not self.aside):
            self.aside.append(rest)
        else:
            self._place(rest)
        self._fill()

    def _place(self, piece: tuple) -> None:
        i = class_of(len(piece[2]) // 4, self.capacity)
        bin_ = self.open.setdefault(i, [])
        bin_.append(piece)
        if len(bin_) == i:
            del self.open[i]
            room = self.capacity - sum(len(p[2]) for p in bin_) // 4
            self.gaps.append((bin_, room)) if room else self._close(bin_)

    def _fill(self) -> None:
        while self.gaps and self.aside:
            bin_, room = self.gaps.pop()
            doc_id, start, ids, total = self.aside.pop()
            n = min(room, len(ids) // 4)
            bin_.append((doc_id, start, ids[: 4 * n], total))
            if 4 * n < len(ids):
                self.aside.append((doc_id, start + n, ids[4 * n :], total))
            self.gaps.append((bin_, room - n)) if n < room else self._close(bin_)

    def finish(self) -> None:
        """Settles the unfilled bins."""
        rest = [p for bin_, _ in self.gaps for p in bin_] + self.aside + [p for i in sorted(self.open) for p in self.open[i]]
        self.open, self.gaps, self.aside = {}, [], []
        left = sum(len(p[2]) // 4 for p in rest)
        room, sequence = 0, []
        for doc_id, start, ids, total in rest:
            while ids:
                if not room:
                    if sequence:
                        self._close(sequence)
                    room, sequence = self.capacity if left >= self.capacity else 1 << left.bit_length() - 1, []
                    left -= room
                n = min(room, len(ids) // 4)
                sequence.append((doc_id, start, ids[: 4 * n], total))
                start, ids, room = start + n, ids[4 * n :], room - n
        if sequence:
            self._close(sequence)

    def rows(self) -> list[tuple]:
        out, self.done = self.done, []
        return out


_coders: dict[str, WordCoder] = {}


def pack(docs: DataFrame, vocabulary: str, capacity: int = CAPACITY, end_id: int = END_ID) -> DataFrame:
    """One row for each piece: doc_id, start, length, ids_crc32, doc_tokens, sequence_id, offset.

    A document's ids end with end_id, so a null or empty text has one. Repeated rows are packed as often as they come, a
    null id stays null, an empty table gives no rows, and other columns aren't read. A sequence is of one worker only; its
    id has the worker's partition in the upper bits, so a task that is run again gives the same rows.
    """
    end = int(end_id).to_bytes(4, "little")

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        if vocabulary not in _coders:
            _coders[vocabulary] = WordCoder(vocabulary)
        coder = _coders[vocabulary]
        packer = HarmonicPacker(capacity, TaskContext.get().partitionId() << 36)
        for part in slices(batches):
            for doc_id, ids in zip(part.column(0).to_pylist(), coder.encode_all([t or "" for t in part.column(1).to_pylist()]), strict=True):
                packer.add(doc_id, ids + end)
            yield _batch(packer.rows())
        packer.finish()
        yield _batch(packer.rows())

    importable(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, SCHEMA)


def _batch(rows: list[tuple]) -> pa.RecordBatch:
    names = [field.split()[0] for field in SCHEMA.split(", ")]
    columns = list(zip(*rows, strict=True)) or [()] * len(names)
    return pa.RecordBatch.from_arrays([pa.array(c, pa.int64()) for c in columns], names)


def padding(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """One row: sequences, tokens, and padded ids as a share of all places."""
    each = pieces.groupBy("sequence_id").agg(F.sum("length").alias("n"))
    power = F.pow(F.lit(2.0), F.floor(F.log2("n"))).cast("long") == F.col("n")
    places = F.when(power, F.col("n")).otherwise(F.lit(capacity))
    return each.agg(F.count("*").alias("sequences"), F.sum("n").alias("tokens"), (1 - F.sum("n") / F.sum(places)).alias("padding"))


def op4(spark: SparkSession, sf_dir: str) -> DataFrame:
    import public_tokenizers

    return pack(documents(spark, sf_dir), public_tokenizers.path("word_bpe_49k.json"))
