"""Near-duplicate documents by circulant MinHash, banding and exact verification on full shingle sets.

A first permutation sends shingles to the places of a circle; the second is one fixed table around that circle, and
coordinate k of a signature is the least table entry k steps after a document's places. So a shingle's share in all
coordinates is one contiguous slice of the table.

Documents of one set are one class, of which only the smallest id goes on. Each class is first compared with the heaviest
members of the buckets that it is in; what that leaves apart is compared across components: members
of buckets whose ends are apart, by the rarest of their shingles, of which any two sets that are similar enough share one.
So no link of a bucket is lost, and pairs inside a component are never made.
"""

from __future__ import annotations

import hashlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import checked, documents, importable, stored, without_rows
from .textkernel import STEP, WHITE_TABLE, mix, runs, shingle_sets, slices, texts_of

QUERY = "op2_minhash_near_dedup"
#: 96 bands of 8 coordinates: at a similarity of 0.75 a pair shares no band once in 25,000 times, at 0.8 once in 45
#: million; texts that share a passage only, at 0.2, meet once in 4,000 times, so buckets hold few strangers.
BANDS, WIDTH = 96, 8
WORDS_IN_SHINGLE = 5
SIMILARITY = 75  # percent
#: Pivots that a class is compared with before components are compared.
PIVOTS = 3
CIRCLE = 1 << 20
SKETCH = "doc_id long, mark long, n_shingles long, digest binary, bands array<long>"
_U = np.uint64

_circle: dict[tuple[int, int], np.ndarray] = {}


def circle(size: int, coordinates: int) -> np.ndarray:
    """The second permutation, followed by its own beginning: row p of the result is the slice that begins at place p."""
    if (size, coordinates) not in _circle:
        table = np.random.Generator(np.random.PCG64(77)).permutation(size).astype(np.uint32)
        _circle[size, coordinates] = np.lib.stride_tricks.sliding_window_view(np.concatenate((table, table[: coordinates - 1])), coordinates)
    return _circle[size, coordinates]


def signature(shingles: np.ndarray, coordinates: int = BANDS * WIDTH, size: int = CIRCLE) -> np.ndarray:
    places, rows = (mix(shingles + STEP[7]) & _U(size - 1)).astype(np.int64), circle(size, coordinates)
    best = rows[places[:2048]].min(axis=0)
    for at in range(2048, len(places), 2048):
        np.minimum(best, rows[places[at : at + 2048]].min(axis=0), out=best)
    return best


def band_keys(signatures: np.ndarray, bands: int = BANDS, width: int = WIDTH) -> np.ndarray:
    """A 64-bit key for each band of each signature; bands don't share keys."""
    parts = signatures.astype(np.uint64).reshape(-1, bands, width)
    key = np.arange(bands, dtype=np.uint64) * STEP[8] + _U(1)
    for k in range(width):
        key = mix(key + parts[:, :, k] * STEP[k])
    return key.astype(np.int64)


def sketches(docs: DataFrame, bands: int = BANDS, width: int = WIDTH) -> DataFrame:
    """doc_id, mark, n_shingles, digest of the whole set (null if empty) and band keys of each text."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            sets = shingle_sets(runs(texts_of(part.column(2)), WHITE_TABLE), WORDS_IN_SHINGLE)
            sizes = [len(s) for s in sets]
            digests = [hashlib.blake2b(s.tobytes(), digest_size=16).digest() if len(s) else None for s in sets]
            full = [s for s in sets if len(s)]
            keys = band_keys(np.stack([signature(s, bands * width) for s in full]), bands, width).ravel() if full else np.empty(0, np.int64)
            offsets = np.concatenate(([0], np.cumsum(np.array(sizes) > 0) * bands)).astype(np.int32)
            yield pa.RecordBatch.from_arrays(
                [part.column(0), part.column(1), pa.array(sizes, pa.int64()), pa.array(digests, pa.binary()), pa.ListArray.from_arrays(pa.array(offsets), pa.array(keys))],
                ["doc_id", "mark", "n_shingles", "digest", "bands"])

    importable(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), F.xxhash64("text").alias("mark"), "text").mapInArrow(run, SKETCH)


def full_sets(docs: DataFrame) -> DataFrame:
    """digest and the sorted distinct shingles of each text, as 64-bit integers end to end."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            sets = [s.tobytes() for s in shingle_sets(runs(texts_of(part.column(0)), WHITE_TABLE), WORDS_IN_SHINGLE)]
            yield pa.RecordBatch.from_arrays([pa.array([hashlib.blake2b(s, digest_size=16).digest() for s in sets], pa.binary()), pa.array(sets, pa.binary())], ["digest", "shingles"])

    return docs.select("text").mapInArrow(run, "digest binary, shingles binary")


def verified(pairs: DataFrame, sets: DataFrame, similarity: int = SIMILARITY) -> DataFrame:
    """The pairs (a, b) whose full sets are similar enough: 100 * intersection >= similarity * union."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keep = []
            for x, y in zip(batch.column(2).to_pylist(), batch.column(3).to_pylist(), strict=True):
                m, n = len(x) // 8, len(y) // 8
                if 100 * min(m, n) < similarity * max(m, n):
                    keep.append(False)
                    continue
                both = np.concatenate((np.frombuffer(x, np.uint64), np.frombuffer(y, np.uint64)))
                both.sort(kind="stable")
                common = int(np.count_nonzero(both[1:] == both[:-1]))
                keep.append(100 * common >= similarity * (m + n - common))
            yield batch.select(["a", "b"]).filter(pa.array(keep, pa.bool_()))

    left = sets.select(F.col("doc_id").alias("a"), F.col("shingles").alias("x"))
    right = sets.select(F.col("doc_id").alias("b"), F.col("shingles").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(run, "a long, b long")


def rare_shingles(sets: DataFrame, docs: DataFrame, similarity: int = SIMILARITY) -> DataFrame:
    """(shingle, doc_id, component, m, rest): of each set of docs (doc_id, m: its size, component, floor: the least size of a
    partner) as many of its rarest shingles as leave fewer than a link needs to have in common. rest is how many the set has from this one on.

    Rarity is counted over these sets, ties by shingle, so two sets that are similar enough share one of these; those that
    no other set has are counted, but not returned. Sets just under the similarity have rare shingles of their own and meet
    few others, however many there are.
    """

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for doc, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                shingles = np.frombuffer(raw.as_buffer(), np.int64)
                for at in range(0, len(shingles), 1 << 18):
                    part = shingles[at : at + (1 << 18)]
                    yield pa.RecordBatch.from_arrays([pa.array(np.full(len(part), doc)), pa.array(part)], ["doc_id", "shingle"])

    each = sets.join(docs, "doc_id", "left_semi").select("doc_id", "shingles").mapInArrow(run, "doc_id long, shingle long")
    shared = each.groupBy("shingle").agg(F.count("*").alias("n")).where("n > 1")
    # 100 * common >= s * union means common >= s * (m + n) / (100 + s); n is at least the floor, and at least s * m / 100.
    need = F.greatest(F.ceil(similarity * (F.col("m") + F.col("floor")) / (100 + similarity) - 1e-6), F.ceil(similarity * F.col("m") / 100 - 1e-6))
    own = Window.partitionBy("doc_id")
    ranked = each.join(shared, "shingle").select("*", F.row_number().over(own.orderBy("n", "shingle")).alias("nth"), F.count("*").over(own).alias("known"))
    chosen = ranked.join(docs, "doc_id").where(F.col("nth") <= F.col("m") - need + 1 - (F.col("m") - F.col("known")))
    return chosen.select("shingle", "doc_id", "component", "m", (F.col("known") - F.col("nth") + 1).alias("rest"))


def components(edges: DataFrame) -> DataFrame:
    """(id, component) of every end of an edge (a, b): component is the smallest id reachable.

    Each round gives every id the least label among itself and its neighbours, then the label of that label, so a chain's
    length is at least halved; ids that are linked to their least member directly need one round.
    """
    ends = stored(edges.select("a", "b").union(edges.select("b", "a")).where("a <> b").distinct(), "ends")
    labels = ends.groupBy(F.col("a").alias("id")).agg(F.least(F.col("id"), F.min("b")).alias("component"))
    labels = stored(labels, "labels")
    while True:
        near = ends.join(labels.withColumnRenamed("id", "b"), "b").groupBy(F.col("a").alias("id")).agg(F.min("component").alias("near"))
        # Hooking: what a component's label is now may itself have learned of a smaller one.
        hooked = labels.join(near, "id").select("id", "component", F.least("component", "near").alias("least"))
        root = hooked.groupBy("component").agg(F.min("least").alias("root"))
        jump = labels.select(F.col("id").alias("root"), F.col("component").alias("beyond"))
        root = root.join(jump, "root", "left").select("component", F.least("root", F.coalesce("beyond", "root")).alias("root"))
        fresh = stored(hooked.join(root, "component").select("id", F.least("least", "root").alias("component"), (F.least("least", "root") < F.col("component")).alias("moved")), "labels")
        labels = fresh.select("id", "component")
        if fresh.where("moved").isEmpty():
            return labels


def near_duplicates(docs: DataFrame, similarity: int = SIMILARITY, bands: int = BANDS, width: int = WIDTH) -> DataFrame:
    """doc_id, n_shingles, component_id and kept of every row of docs.

    A text without words (null, empty, white space) has an empty set and is linked with nothing; a text of fewer than five
    words is one shingle. Repeated rows have equal sets, so they share a component; an id with several texts has a row and
    a component for each; rows with a null id take no part and have a null component. An empty table gives no rows; other
    columns aren't read.
    """
    out = _judged(docs, similarity, bands, width)
    return out.select("doc_id", "n_shingles", "component_id", "kept")


def _judged(docs: DataFrame, similarity: int = SIMILARITY, bands: int = BANDS, width: int = WIDTH) -> DataFrame:
    """near_duplicates() with mark, a hash of the text, which tells rows of one id apart."""
    # Inside, a set is known by one row that has it, as an id may come with several texts: doc_id means that row from here on.
    sketch = stored(sketches(docs, bands, width).withColumn("_row", F.monotonically_increasing_id()), "sketches")
    real = sketch.where("digest is not null and doc_id is not null")
    groups = stored(real.groupBy("digest").agg(F.min("_row").alias("rep"), F.min("doc_id").alias("least")), "sets")
    reps = real.select(F.col("_row").alias("doc_id"), "bands").join(groups.select(F.col("rep").alias("doc_id")), "doc_id", "left_semi")
    entries = stored(reps.select("doc_id", F.explode("bands").alias("key")), "band-entries")
    buckets = entries.groupBy("key").agg(F.min("doc_id").alias("least"), F.max("doc_id").alias("last")).where("least < last").select("key")
    members = stored(entries.join(buckets, "key"), "bucket-members")
    ids = stored(members.select("doc_id").distinct(), "candidates")
    wanted = stored(sketch.select(F.col("_row").alias("doc_id"), F.col("doc_id").alias("id"), "digest").join(checked(ids), "doc_id", "left_semi"), "candidate-sets")
    texts = docs.join(checked(wanted.select(F.col("id").alias("doc_id")).distinct()), "doc_id", "left_semi")
    sets = stored(full_sets(texts).dropDuplicates(["digest"]).join(wanted.select("doc_id", "digest"), "digest").select("doc_id", "shingles"), "full-sets")

    # A bucket's pivot is its heaviest member, by the sizes of all buckets it is in: the text that others were copied from
    # is in more and larger buckets than they are, so comparing with it leaves few of a group apart.
    full = members.groupBy("key").agg(F.count("*").alias("n"))
    weight = members.join(full, "key").groupBy("doc_id").agg(F.sum("n").alias("weight"))
    weighed = stored(members.join(weight, "doc_id").select("key", "doc_id", "weight"), "weighed")
    heavy = weighed.groupBy("key").agg(F.max(F.struct("weight", (-F.col("doc_id")).alias("less"))).alias("top"))
    heavy = heavy.select("key", (-F.col("top.less")).alias("pivot"), F.col("top.weight").alias("pivot_weight"))
    stars = weighed.select("key", "doc_id").join(heavy, "key").where("doc_id <> pivot").select("doc_id", "pivot", "pivot_weight").distinct()
    nth = F.row_number().over(Window.partitionBy("doc_id").orderBy(F.desc("pivot_weight"), "pivot"))  # one row a band at most
    best = stars.withColumn("nth", nth).where(F.col("nth") <= PIVOTS)
    first = stored(verified(best.select(F.col("doc_id").alias("a"), F.col("pivot").alias("b")), sets, similarity), "star-links")
    near = components(first)

    sizes = real.select(F.col("_row").alias("doc_id"), "n_shingles").join(checked(ids), "doc_id", "left_semi")
    placed = members.select("key", "doc_id").join(sizes, "doc_id").join(near.withColumnRenamed("id", "doc_id"), "doc_id", "left")
    placed = stored(placed.select("key", "doc_id", "n_shingles", F.coalesce("component", "doc_id").alias("component")), "placed")
    split = placed.groupBy("key").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("key")
    apart = stored(placed.join(split, "key", "left_semi"), "apart")
    floor = apart.groupBy("key").agg(F.min("n_shingles").alias("floor"))
    open_ = apart.join(floor, "key").groupBy("doc_id").agg(F.max("n_shingles").alias("m"), F.max("component").alias("component"), F.min("floor").alias("floor"))
    live = stored(rare_shingles(sets, stored(open_, "open"), similarity), "rare-shingles")
    split = live.groupBy("shingle").agg(F.min("component").alias("lo"), F.max("component").alias("hi")).where("lo < hi").select("shingle")
    live = stored(live.join(split, "shingle", "left_semi"), "rare-shared")
    parts = live.groupBy("shingle", "component").agg(F.min("m").alias("least"), F.max("m").alias("most"), F.max("rest").alias("rest"))
    other = parts.select("shingle", F.col("component").alias("other"), F.col("least").alias("least2"), F.col("most").alias("most2"), F.col("rest").alias("rest2"))
    sized = (100 * F.col("most2") >= similarity * F.col("least")) & (100 * F.col("most") >= similarity * F.col("least2"))
    # Of two sets' first common shingle in order of rarity: no more are in common than what either has from there on.
    sized &= (100 + similarity) * F.least("rest", "rest2") >= similarity * (F.col("least") + F.col("least2"))
    across = parts.join(other, "shingle").where((F.col("component") < F.col("other")) & sized)
    across = across.select("shingle", "component", "other", F.col("least2").alias("least_other"), F.col("rest2").alias("rest_other"))
    left = live.select("shingle", "component", F.col("doc_id").alias("a"), "m", "rest")
    right = live.select("shingle", F.col("component").alias("other"), F.col("doc_id").alias("b"), F.col("m").alias("n"), F.col("rest").alias("rest2"))
    fits = (100 * F.least("m", "n") >= similarity * F.greatest("m", "n")) & ((100 + similarity) * F.least("rest", "rest2") >= similarity * (F.col("m") + F.col("n")))
    some = (100 + similarity) * F.least("rest", "rest_other") >= similarity * (F.col("m") + F.col("least_other"))  # else a member fits none of the other part
    pairs = across.join(left, ["shingle", "component"]).where(some).join(right, ["shingle", "other"]).where(fits)
    second = stored(verified(stored(pairs.select("a", "b").distinct(), "pairs"), sets, similarity), "cross-links")
    linked = components(first.union(second))

    ofset = groups.join(linked.withColumnRenamed("id", "rep"), "rep", "left").select("digest", "least", F.coalesce("component", "rep").alias("component"))
    least = ofset.groupBy("component").agg(F.min("least").alias("found"))
    named = stored(ofset.select("digest", "component").join(least, "component").select("digest", "found"), "set-components")
    out = sketch.select("doc_id", "mark", "n_shingles", "digest").join(named, "digest", "left")
    component = F.when(F.col("doc_id").isNotNull(), F.coalesce("found", "doc_id"))
    return out.select("doc_id", "mark", "n_shingles", component.alias("component_id"), F.coalesce(component == F.col("doc_id"), F.lit(True)).alias("kept"))


def drop_near_copies(docs: DataFrame, similarity: int = SIMILARITY) -> DataFrame:
    """The rows of docs that stay: of each component those with the smallest id. Rows with a null id stay."""
    rejected = stored(_judged(docs, similarity).where("not kept").select("doc_id", "mark").distinct(), "near-copies")
    return without_rows(docs, rejected, F.xxhash64("text"))


def op2(spark: SparkSession, sf_dir: str) -> DataFrame:
    return near_duplicates(documents(spark, sf_dir))
