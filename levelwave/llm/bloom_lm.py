"""N-gram scoring by a log-frequency Bloom filter of quantised counts, broadcast to workers.

Tasks send each segment of the hash space one sorted block of n-gram hashes with their counts. A segment adds its blocks up
and enters every n-gram at once: one of count c for each level up to its logarithm. So the filter is made where the counts
meet, of all n-grams, and only its bits are kept. A lookup probes level after level until one is missing. The number of
segments follows the text, so no group that a task holds grows with it.

Up to a bound the filter is broadcast; beyond it the segments stay where they are, and the n-grams of each block of texts
are sent there and their levels back. Both ways give the same scores. Exact counts of the commonest words are broadcast
beside the filter (a fixed number at most); other words are looked up by a shuffled join, so base scores are exact.
"""

from __future__ import annotations

import math
from collections.abc import Callable, Iterator
from dataclasses import dataclass

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .shared import crc_bucket, documents, importable, stored
from .textkernel import STEP, WHITE_TABLE, Texts, mix, runs, slices, texts_of

QUERY = "op7_bloom_lm"
#: Words whose exact count is broadcast at most (16 bytes each), and bytes of a filter that is broadcast at most.
HEAD_WORDS, FILTER_BYTES = 1 << 20, 128 << 20
#: Bytes of text whose n-grams share a segment, about: some five million, 50 MB of them before they are added up.
SEGMENT_TEXT = 32 << 20
#: Hash probes of a level; bits of the filter for each entry; base of the quantisation.
PROBES, BITS_PER_ENTRY, LOG_BASE = 4, 10, 2.0
#: Weight of the pair model where the first word is known.
PAIR_WEIGHT = 0.6
SMOOTH = 0.1
#: Hashes that a task gathers before it adds up and sends.
BUFFER = 4_000_000
#: Tokens of a block of texts whose n-grams are looked up together (one longer text is a block of its own).
BLOCK = 1 << 20
_U = np.uint64
END, BEGIN = _U(0x1F3D5B79A2C4E6F1), _U(0x7A5C3E1F9B8D6042)


def tokens(texts: Texts) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(text, hash, hash of the one before) of every token: a text's words, then its end."""
    words = runs(texts, WHITE_TABLE)
    n = len(texts)
    doc = np.concatenate((words.doc, np.arange(n)))
    order = np.argsort(doc, kind="stable")  # ends come after the words of their text
    doc, hashes = doc[order], np.concatenate((words.hash, np.full(n, END)))[order]
    return doc, hashes, _before(doc, hashes)


def _before(doc: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    before = np.empty_like(hashes)
    before[1:] = hashes[:-1]
    before[:1] = BEGIN
    before[1:][doc[1:] != doc[:-1]] = BEGIN
    return before


def pair_hash(first: np.ndarray, second: np.ndarray) -> np.ndarray:
    return mix(first * STEP[1] + second * STEP[2] + _U(3))


def segment_of(keys: np.ndarray, segments: int) -> np.ndarray:
    """Equal ranges of the hash space, so sorted keys lie in order of segments."""
    return ((keys >> _U(32)) * _U(segments) >> _U(32)).astype(np.int64)


def planes(values: np.ndarray) -> bytes:
    """Numbers byte by byte, all highest bytes together: where those are zeros, compression takes them out."""
    return values.view(np.uint8).reshape(-1, values.itemsize).T.tobytes()


def from_planes(raw: bytes, dtype: type) -> np.ndarray:
    size = np.dtype(dtype).itemsize
    return np.ascontiguousarray(np.frombuffer(raw, np.uint8).reshape(size, -1).T).view(dtype).ravel()


def packed(keys: np.ndarray) -> bytes:
    """Sorted keys by their differences."""
    return planes(np.diff(keys, prepend=_U(0)))


def unpacked(raw: bytes) -> np.ndarray:
    return np.cumsum(from_planes(raw, np.uint64), dtype=np.uint64)


def _added(keys: np.ndarray, counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    order = np.argsort(keys)
    keys, counts = keys[order], counts[order]
    if not len(keys):
        return keys, counts
    first = np.flatnonzero(np.concatenate(([True], keys[1:] != keys[:-1])))
    return keys[first], np.add.reduceat(counts, first)


def _levels(counts: np.ndarray) -> np.ndarray:
    """1 for a count of 1, one more for each factor of LOG_BASE."""
    return 1 + np.floor(np.log(np.maximum(counts, 1)) / math.log(LOG_BASE) + 1e-9).astype(np.int64)


def _least(levels: np.ndarray) -> np.ndarray:
    """The least count of a level; 0 for level 0."""
    return np.where(levels > 0, np.ceil(LOG_BASE ** (levels - 1.0) - 1e-9), 0.0)


def _most(levels: np.ndarray) -> np.ndarray:
    """The greatest count of a level; 0 for level 0."""
    return np.where(levels > 0, np.ceil(LOG_BASE**levels - 1e-9) - 1, 0.0)


def _probes(keys: np.ndarray, level: int) -> tuple[np.ndarray, np.ndarray]:
    h = mix(keys + STEP[9:10] * _U(level))
    return h >> _U(32), h & _U(0xFFFFFFFF) | _U(1)


def _place(start: np.ndarray, step: np.ndarray, probe: int, bits: int | np.ndarray) -> np.ndarray:
    return (((start + _U(probe) * step & _U(0xFFFFFFFF)) * np.asarray(bits, np.uint64)) >> _U(32)).astype(np.int64)


def filled(keys: np.ndarray, counts: np.ndarray) -> np.ndarray:
    """The segment, 8 bits a byte, that these n-grams fill; its size follows their number."""
    levels = _levels(counts)
    bits = max(64, -(-int(levels.sum()) * BITS_PER_ENTRY // 64) * 64)
    segment = np.zeros(bits, dtype=bool)
    for level in range(1, int(levels.max(initial=0)) + 1):
        start, step = _probes(keys[levels >= level], level)
        for probe in range(PROBES):
            segment[_place(start, step, probe, bits)] = True
    return np.packbits(segment, bitorder="little")


@dataclass
class LogFrequencyFilter:
    """Segments end to end: that of number s has the bytes from first[s] to first[s + 1]."""

    data: np.ndarray
    first: np.ndarray

    @classmethod
    def of(cls, segments: list[np.ndarray]) -> LogFrequencyFilter:
        return cls(np.concatenate([np.empty(0, np.uint8), *segments]), np.cumsum([0, *map(len, segments)]))

    def levels(self, keys: np.ndarray) -> np.ndarray:
        """By probes of level 1, 2, ... until one is missing."""
        out = np.zeros(len(keys), dtype=np.int64)
        at = segment_of(keys, len(self.first) - 1) if len(self.first) > 2 else np.zeros(len(keys), np.int64)
        live, level = np.flatnonzero(np.diff(self.first)[at] > 0) if len(self.first) > 1 else np.empty(0, np.int64), 1
        base, bits = self.first[at] * 8, (np.diff(self.first) * 8).astype(np.uint64)[at] if len(self.first) > 1 else None
        while len(live) and level < 64:
            start, step = _probes(keys[live], level)
            for probe in range(PROBES):
                place = base[live] + _place(start, step, probe, bits[live])
                hit = (self.data[place >> 3] >> (place & 7).astype(np.uint8)) & 1 == 1
                live, start, step = live[hit], start[hit], step[hit]
            out[live] = level
            level += 1
        return out


def segments_for(docs: DataFrame) -> int:
    """So many that each has the n-grams of some SEGMENT_TEXT bytes, and no fewer than shuffles have partitions."""
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    return max(16, int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), -(-size // SEGMENT_TEXT))


def _blocks(docs: DataFrame, segments: int) -> DataFrame:
    """(segment, kind, keys, counts): kind 1 words, 2 pairs; packed hashes and planes of 32-bit counts."""

    def flush(gathered: dict[int, list[np.ndarray]]) -> Iterator[pa.RecordBatch]:
        for kind, parts in gathered.items():
            if not parts:
                continue
            keys, counts = np.unique(np.concatenate(parts), return_counts=True)
            counts = counts.astype(np.uint32)
            cuts = np.searchsorted(segment_of(keys, segments), np.arange(segments + 1))
            full = np.flatnonzero(np.diff(cuts))
            yield pa.RecordBatch.from_arrays(
                [pa.array(full, pa.int32()), pa.array(np.full(len(full), kind), pa.int32()), pa.array([packed(keys[cuts[s] : cuts[s + 1]]) for s in full], pa.binary()), pa.array([planes(counts[cuts[s] : cuts[s + 1]]) for s in full], pa.binary())],
                ["segment", "kind", "keys", "counts"])
            parts.clear()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        gathered: dict[int, list[np.ndarray]] = {1: [], 2: []}
        held = 0
        for part in slices(batches):
            _, hashes, before = tokens(texts_of(part.column(0)))
            gathered[1].append(hashes)
            gathered[2].append(pair_hash(before, hashes))
            held += len(hashes)
            if held > BUFFER:
                yield from flush(gathered)
                held = 0
        yield from flush(gathered)

    return docs.select("text").mapInArrow(run, "segment int, kind int, keys binary, counts binary")


def learned(docs: DataFrame, segments: int) -> DataFrame:
    """(segment, bits, words, counts, n, total, histogram), stored: each segment's part of the filter, of all its words and
    pairs, and its words with their exact counts, number, sum, and number by level."""

    def add(table: pa.Table) -> pa.Table:
        kinds, found = table.column("kind").to_numpy(), []
        for kind in (1, 2):
            rows = table.take(pa.array(np.flatnonzero(kinds == kind)))
            keys = np.concatenate([np.empty(0, np.uint64), *(unpacked(k.as_buffer()) for k in rows.column("keys"))])
            counts = np.concatenate([np.empty(0, np.uint32), *(from_planes(c.as_buffer(), np.uint32) for c in rows.column("counts"))])
            found.append(_added(keys, counts.astype(np.int64)))
        (words, n), (pairs, m) = found
        segment = filled(np.concatenate((words, pairs)), np.concatenate((n, m)))
        by_level = np.bincount(_levels(n), minlength=64)[:64]
        row = (int(table.column("segment")[0].as_py()), segment.tobytes(), packed(words), planes(n), len(n), int(n.sum()), by_level.tolist())
        types = [pa.int32(), pa.binary(), pa.binary(), pa.binary(), pa.int64(), pa.int64(), pa.list_(pa.int64())]
        return pa.Table.from_arrays([pa.array([c], t) for c, t in zip(row, types, strict=True)], names=["segment", "bits", "words", "counts", "n", "total", "histogram"])

    importable(docs.sparkSession)
    blocks = _blocks(docs, segments).repartition(min(segments, 1 << 16), "segment")
    schema = "segment int, bits binary, words binary, counts binary, n long, total long, histogram array<long>"
    return stored(blocks.groupBy("segment").applyInArrow(lambda t: add(t), schema), "lm-segments")


@dataclass
class Model:
    """filter is None where the segments stay apart."""

    filter: LogFrequencyFilter | None
    total: int
    distinct: int
    head: np.ndarray
    head_counts: np.ndarray
    complete: bool

    @property
    def unit(self) -> float:
        return self.total + SMOOTH * (self.distinct + 1)


def build(parts: DataFrame, segments: int, filter_bytes: int = FILTER_BYTES, head_words: int = HEAD_WORDS) -> Model:
    """Sums, head and, within filter_bytes, the filter. Nothing else comes to the driver, all of bounded size."""
    sums = parts.agg(F.sum("n"), F.sum("total"), F.sum(F.octet_length("bits")), *[F.sum(F.col("histogram")[i]) for i in range(1, 64)]).first()
    distinct, total, size, *histogram = (int(x or 0) for x in sums)
    known = np.cumsum(histogram[::-1])[::-1]  # words of each level or more
    head_level = next(i for i in range(1, 65) if i == 64 or known[i - 1] <= head_words)

    def common(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for words, found in zip(batch.column(0), batch.column(1), strict=True):
                keys, found = unpacked(words.as_buffer()), from_planes(found.as_buffer(), np.int64)
                keep = _levels(found) >= head_level
                yield pa.RecordBatch.from_arrays([pa.array([keys[keep].tobytes()], pa.binary()), pa.array([found[keep].tobytes()], pa.binary())], ["keys", "counts"])

    whole = None
    if size <= filter_bytes:
        bits = [np.empty(0, np.uint8)] * segments
        for row in parts.select("segment", "bits").toLocalIterator():
            bits[row["segment"]] = np.frombuffer(row["bits"], np.uint8)
        whole = LogFrequencyFilter.of(bits)
    rows = parts.select("words", "counts").mapInArrow(common, "keys binary, counts binary").collect()
    head = np.concatenate([np.empty(0, np.uint64), *(np.frombuffer(r["keys"], np.uint64) for r in rows)])
    head_counts = np.concatenate([np.empty(0, np.int64), *(np.frombuffer(r["counts"], np.int64) for r in rows)])
    order = np.argsort(head)
    return Model(whole, total, distinct, head[order], head_counts[order], len(head) == distinct)


def _exact(model: Model, keys: np.ndarray) -> np.ndarray:
    """Counts of words in the head; -1 where another place must be asked, 0 where it need not."""
    if not len(model.head):
        return np.full(len(keys), 0 if model.complete else -1)
    at = np.minimum(np.searchsorted(model.head, keys), len(model.head) - 1)
    return np.where(model.head[at] == keys, model.head_counts[at], 0 if model.complete else -1)


def score_tokens(model: Model, n: int, doc: np.ndarray, hashes: np.ndarray, before: np.ndarray, levels: Callable[[np.ndarray], np.ndarray]) -> tuple[np.ndarray, ...]:
    """n_tokens, n_known, base and score of each of n texts by head and levels; then (text, word, times) left to a join.

    A token's probability is PAIR_WEIGHT of the pair's share of its first word's count and the rest of the smoothed word
    model, or that model alone after an unknown word. Pairs and words count with the least of their level, first words with
    the greatest (exactly where in the head), so over all words the probabilities add up to 1 at most.
    """
    keys, which = np.unique(hashes, return_inverse=True)
    exact = _exact(model, keys)
    settled = exact[which] >= 0
    base = np.bincount(doc[settled], np.log10((exact[which[settled]] + SMOOTH) / model.unit), minlength=n).astype(float)  # of none it is whole numbers
    known = np.bincount(doc[exact[which] > 0], minlength=n)
    least, most = exact.astype(float), exact.astype(float)
    if len(rare := np.flatnonzero(exact < 0)):
        found = levels(keys[rare])
        least[rare], most[rare] = _least(found), _most(found)
    single = (least[which] + SMOOTH) / model.unit
    # Every word but a text's first follows one of the text; before that is the beginning, as frequent as ends are.
    first = np.concatenate(([0.0], most[which[:-1]])) if len(which) else most[which]
    first[before == BEGIN] = most[np.searchsorted(keys, END)] if len(keys) else 0.0
    pair_keys, pair_which = np.unique(pair_hash(before, hashes), return_inverse=True)
    share = np.minimum(_least(levels(pair_keys))[pair_which] / np.maximum(first, 1), 1.0)
    weight = np.where(first > 0, PAIR_WEIGHT, 0.0)
    score = np.bincount(doc, np.log10(weight * share + (1 - weight) * single), minlength=n)
    rest_key, times = np.unique(np.stack((doc[~settled].astype(np.uint64), hashes[~settled])), axis=1, return_counts=True) if not settled.all() else (np.empty((2, 0), np.uint64), np.empty(0, np.int64))
    return np.bincount(doc, minlength=n), known, base, score, rest_key[0].astype(np.int64), rest_key[1], times


_SCORED = "_row long, doc_id long, n_tokens long, n_known long, base double, score double, words array<long>, times array<long>"


def _scored(rows: pa.Array, ids: pa.Array, found: tuple[np.ndarray, ...]) -> pa.RecordBatch:
    n_tokens, known, base, score, of, words, times = found
    cuts = np.searchsorted(of, np.arange(len(rows) + 1)).astype(np.int32)
    lists = [pa.ListArray.from_arrays(pa.array(cuts), v) for v in (pa.array(words.view(np.int64)), pa.array(times, pa.int64()))]
    return pa.RecordBatch.from_arrays([rows, ids, pa.array(n_tokens, pa.int64()), pa.array(known, pa.int64()), pa.array(base), pa.array(score), *lists], ["_row", "doc_id", "n_tokens", "n_known", "base", "score", "words", "times"])


def _token_blocks(rows: DataFrame) -> DataFrame:
    """(block, rows, ids, sizes, words, codes), stored: sizes has the tokens of each text, codes all of them by number in
    words, which has each hash once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        place, held, size = TaskContext.get().partitionId() << 32, [], 0

        def block() -> pa.RecordBatch:
            row, ids, sizes, hashes = zip(*held, strict=True)
            words, codes = np.unique(np.concatenate(hashes), return_inverse=True)
            return pa.RecordBatch.from_arrays(
                [pa.array([place], pa.int64()), pa.array([sum(row, [])], pa.list_(pa.int64())), pa.array([sum(ids, [])], pa.list_(pa.int64())), pa.array([np.concatenate(sizes).tolist()], pa.list_(pa.int64())),
                 pa.array([packed(words)], pa.binary()), pa.array([planes(codes.astype(np.uint32))], pa.binary())],
                ["block", "rows", "ids", "sizes", "words", "codes"])

        for part in slices(batches):
            doc, hashes, _ = tokens(texts_of(part.column(2)))
            held.append((part.column(0).to_pylist(), part.column(1).to_pylist(), np.bincount(doc, minlength=part.num_rows), hashes))
            size += len(hashes)
            if size >= BLOCK:
                yield block()
                place, held, size = place + 1, [], 0
        if held:
            yield block()

    return stored(rows.mapInArrow(run, "block long, rows array<long>, ids array<long>, sizes array<long>, words binary, codes binary"), "lm-blocks")


def _tokens_of(sizes: np.ndarray, words: pa.Scalar, codes: pa.Scalar) -> tuple[np.ndarray, np.ndarray, np.ndarray, np.ndarray]:
    """(text, hash, hash of the one before) of every token of a block; then its n-grams, each once, sorted."""
    names = unpacked(words.as_buffer())
    hashes = names[from_planes(codes.as_buffer(), np.uint32)]
    doc = np.repeat(np.arange(len(sizes)), sizes)
    before = _before(doc, hashes)
    return doc, hashes, before, np.unique(np.concatenate((names, pair_hash(before, hashes))))


def _scored_by_segments(rows: DataFrame, parts: DataFrame, segments: int, model: Model) -> DataFrame:
    """_SCORED of all rows (_row, doc_id, text): each block asks every segment for the levels of its n-grams there."""
    sent = rows.sparkSession.sparkContext.broadcast(model)
    blocks = _token_blocks(rows)

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for i in range(batch.num_rows):  # row by row, as rows are large
                block, sizes, words, codes = (c[i] for c in batch.columns)
                keys = _tokens_of(sizes.values.to_numpy(), words, codes)[3]
                cuts = np.searchsorted(segment_of(keys, segments), np.arange(segments + 1))
                full = np.flatnonzero(np.diff(cuts))
                yield pa.RecordBatch.from_arrays([pa.array(full, pa.int32()), pa.array(np.full(len(full), block.as_py()), pa.int64()), pa.array([packed(keys[cuts[s] : cuts[s + 1]]) for s in full], pa.binary())], ["segment", "block", "asked"])

    def answer(known: pa.Table, asked: pa.Table) -> pa.Table:
        one = LogFrequencyFilter.of([np.frombuffer(b.as_buffer(), np.uint8) for b in known.column("bits")])
        levels = [one.levels(unpacked(a.as_buffer())).astype(np.uint8).tobytes() for a in asked.column("asked")]
        return pa.table({"block": asked.column("block"), "segment": asked.column("segment"), "levels": pa.array(levels, pa.binary())})

    def score(block: pa.Table, answers: pa.Table) -> pa.Table:
        sizes = block.column("sizes").combine_chunks().flatten().to_numpy()
        doc, hashes, before, keys = _tokens_of(sizes, block.column("words")[0], block.column("codes")[0])
        by_segment = dict(zip(answers.column("segment").to_pylist(), answers.column("levels").to_pylist(), strict=True))
        levels = np.frombuffer(b"".join(by_segment[s] for s in sorted(by_segment)), np.uint8).astype(np.int64)
        found = score_tokens(sent.value, len(sizes), doc, hashes, before, lambda k: levels[np.searchsorted(keys, k)])
        return pa.Table.from_batches([_scored(block.column("rows").combine_chunks().flatten(), block.column("ids").combine_chunks().flatten(), found)])

    asked = blocks.select("block", "sizes", "words", "codes").mapInArrow(ask, "segment int, block long, asked binary")
    answers = parts.select("segment", "bits").groupBy("segment").cogroup(asked.groupBy("segment")).applyInArrow(lambda a, b: answer(a, b), "block long, segment int, levels binary")
    return blocks.groupBy("block").cogroup(answers.groupBy("block")).applyInArrow(lambda a, b: score(a, b), _SCORED)


def bloom_scores(docs: DataFrame, segments: int | None = None, modulus: int = 10) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score and score of every row.

    Learned from rows whose crc32 of the id modulo 10 isn't 0 (null ids are held out). A null or empty text is its end
    alone. With nothing to learn from, every count is 0. Repeated rows count as often as they come and are scored alike.
    """
    spark = docs.sparkSession
    training = docs.where(crc_bucket(F.col("doc_id"), modulus) != 0)
    segments = segments or segments_for(training)
    parts = learned(training, segments)
    model = build(parts, segments)
    rows = docs.select(F.monotonically_increasing_id().alias("_row"), F.col("doc_id").cast("long"), "text")
    if model.filter is None:
        scored = _scored_by_segments(rows, parts, segments, model)
    else:
        sent = spark.sparkContext.broadcast(model)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            m = sent.value
            for part in slices(batches):
                found = score_tokens(m, part.num_rows, *tokens(texts_of(part.column(2))), m.filter.levels)
                yield _scored(part.column(0), part.column(1), found)

        scored = rows.mapInArrow(run, _SCORED)
    if model.complete:
        out = scored.select("doc_id", "n_tokens", "n_known", F.col("base").alias("base_score"), "score")
    else:
        scored = stored(scored, "lm-scores")
        asked = scored.select("_row", F.explode(F.arrays_zip("words", "times")).alias("w")).select("_row", F.col("w.words").alias("word"), F.col("w.times").alias("times"))
        answers = asked.join(_rare_words(parts, model), "word", "left").groupBy("_row").agg(
            F.sum(F.col("times") * F.log10((F.coalesce("count", F.lit(0)) + F.lit(SMOOTH)) / F.lit(model.unit))).alias("more"),
            F.sum(F.when(F.col("count") > 0, F.col("times")).otherwise(0)).alias("found"))
        out = scored.drop("words", "times").join(answers, "_row", "left").select(
            "doc_id", "n_tokens", (F.col("n_known") + F.coalesce("found", F.lit(0))).alias("n_known"), (F.col("base") + F.coalesce("more", F.lit(0.0))).alias("base_score"), "score")
    return out.select("doc_id", (crc_bucket(F.col("doc_id"), modulus) == 0).alias("held_out"), "n_tokens", "n_known", F.lit(model.total).cast("long").alias("train_tokens"), "base_score", "score")


def _rare_words(parts: DataFrame, model: Model) -> DataFrame:
    """(word, count) of the words that aren't in the head, one row each."""
    least = int(model.head_counts.min()) if len(model.head_counts) else 1 << 62

    def rows(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for words, found in zip(batch.column(0), batch.column(1), strict=True):
                keys, found = unpacked(words.as_buffer()).view(np.int64), from_planes(found.as_buffer(), np.int64)
                keep = found < least
                yield pa.RecordBatch.from_arrays([pa.array(keys[keep]), pa.array(found[keep])], ["word", "count"])

    return parts.select("words", "counts").mapInArrow(rows, "word long, count long")


def op7(spark: SparkSession, sf_dir: str) -> DataFrame:
    return bloom_scores(documents(spark, sf_dir))
