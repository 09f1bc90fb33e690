"""Quality rules: fixed base rules, then robust multivariate outliers for each language and source.

Six statistics of a document, on a log scale, make its vector. Each cell (language and source; small cells are pooled by
language, then all together) gets a minimum-covariance-determinant estimate. It is looked for from three starts: medians
with quartile ranges, and with the covariances of signs and of squashed values. Each step keeps the three quarters of the
rows that are nearest by the present estimate and takes their mean and covariance, which lowers the determinant. After two
steps the start of the least determinant goes on alone, until its determinant stays; then mean and covariance of all rows
within the 0.975 quantile take its place. A document is rejected where its Mahalanobis distance is far beyond what a normal
cell would show. All steps are sums over all rows, combined before they are shuffled, so a hot cell is no single task's work.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .shared import checked, documents, importable, row_mark, stored, without_rows
from .textkernel import STEP, WHITE_TABLE, Texts, mix, runs, sequence_hash, slices, table, texts_of

QUERY = "op6_quality_outliers"
#: Share of a cell's rows in the estimate; steps of each start; then at most so many more, until the logarithm of each
#: determinant changes by less; rows of a cell that is estimated by itself; quantile of the rows that are weighed in at last.
SHARE, FIRST_STEPS, MORE_STEPS, SETTLED, CELL_ROWS, WEIGHED = 0.75, 2, 20, 1e-3, 60, 0.975
#: Chance that a document of a normal cell is rejected, and the least deviation taken as natural, on the log scale.
TAIL, FLOOR = 1e-3, 0.3
#: Added to a share before its logarithm: word length, symbols, other marks, capitals, repeated words, repeated lines.
OFFSETS = (0.0, 0.01, 0.02, 0.02, 0.1, 0.1)
D = len(OFFSETS)
COUNTS = ["n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words"]
_U = np.uint64
_SYMBOLS, _NEWLINE = table(b"#*$%&|<>"), table(b"\n")
_MARKS = table(bytes(b for b in range(33, 127) if not chr(b).isalnum() and chr(b) not in "#*$%&|<>"))
_CAPITALS = table(bytes(range(65, 91)))


def _per_text(flags: np.ndarray, bounds: np.ndarray) -> np.ndarray:
    return np.diff(np.concatenate(([0], np.cumsum(flags)))[bounds])


def statistics(texts: Texts) -> dict[str, np.ndarray]:
    """The five counts of each text, n_lines, and the six log statistics x (0 where there are no words)."""
    data, bounds, n = texts.data, texts.bounds, len(texts)
    words = runs(texts, WHITE_TABLE, lower=False)
    lines = runs(texts, _NEWLINE, lower=False)
    n_words = np.diff(words.first)
    chars = _per_text(((data & 0xC0) != 0x80) & ~WHITE_TABLE[data], bounds)

    full = np.searchsorted(words.start, lines.start) < np.searchsorted(words.start, lines.end)
    line_doc = lines.doc[full]
    _, seen = np.unique(mix(lines.hash[full] + line_doc.astype(np.uint64) * STEP[5]), return_index=True)
    n_lines = np.bincount(line_doc, minlength=n)
    n_dup = n_lines - np.bincount(line_doc[seen], minlength=n)

    grams = sequence_hash(words.hash, 5)
    at = np.flatnonzero(words.doc[: len(grams)] == words.doc[4:]) if len(grams) else np.empty(0, np.int64)
    _, which, times = np.unique(mix(grams[at] + words.doc[at].astype(np.uint64) * STEP[6]), return_inverse=True, return_counts=True)
    twice = at[times[which] > 1]
    cover = np.zeros(len(words.doc) + 1, dtype=np.int64)
    cover[twice] += 1
    cover[twice + 5] -= 1
    n_repeat = np.bincount(words.doc[np.cumsum(cover)[:-1] > 0], minlength=n)

    symbols, marks, capitals = (_per_text(t[data], bounds) for t in (_SYMBOLS, _MARKS, _CAPITALS))
    c, w = np.maximum(chars, 1), np.maximum(n_words, 1)
    shares = [c / w, symbols / c, marks / c, capitals / c, n_repeat / w, n_dup / np.maximum(n_lines, 1)]
    x = np.stack([np.log(s + o) for s, o in zip(shares, OFFSETS, strict=True)], axis=1)
    return {"n_words": n_words, "word_chars": chars, "n_symbols": symbols, "n_dup_lines": n_dup, "n_repeat_words": n_repeat, "x": x}


def measured(docs: DataFrame) -> DataFrame:
    """doc_id, mark, lang, source, the five counts, base_failed and x0..x5 of every row. A null text has no words."""
    names = ["doc_id", "mark", "lang", "source", *COUNTS, "base_failed", *(f"x{i}" for i in range(D))]
    schema = "doc_id long, mark long, lang string, source string, " + ", ".join(f"{c} long" for c in COUNTS) + ", base_failed boolean, " + ", ".join(f"x{i} double" for i in range(D))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for part in slices(batches):
            s = statistics(texts_of(part.column(4)))
            failed = (s["n_words"] < 10) | (100 * s["n_repeat_words"] > 20 * s["n_words"])
            yield pa.RecordBatch.from_arrays([*(part.column(i) for i in range(4)), *(pa.array(s[c].astype(np.int64)) for c in COUNTS), pa.array(failed), *(pa.array(s["x"][:, i]) for i in range(D))], names)

    importable(docs.sparkSession)
    return docs.select(F.col("doc_id").cast("long"), row_mark().alias("mark"), F.col("lang").cast("string"), F.col("source").cast("string"), "text").mapInArrow(run, schema)


def chi2_cdf(x: float, degrees: int) -> float:
    """For an even number of degrees of freedom."""
    term, total = 1.0, 0.0
    for k in range(degrees // 2):
        total += term
        term *= x / 2 / (k + 1)
    return 1 - math.exp(-x / 2) * total


def chi2_tail_point(tail: float, degrees: int) -> float:
    """Where the upper tail has this chance (even degrees of freedom)."""
    lo, hi = 0.0, 1e4

    def upper(x: float) -> float:
        term, total = 1.0, 0.0
        for k in range(degrees // 2):
            total += term
            term *= x / 2 / (k + 1)
        return math.exp(-x / 2) * total

    for _ in range(200):
        mid = (lo + hi) / 2
        lo, hi = (mid, hi) if upper(mid) > tail else (lo, mid)
    return hi


def consistency(share: float = SHARE, degrees: int = D) -> float:
    """Factor by which the covariance of the nearest share of normal rows is too small."""
    return share / chi2_cdf(chi2_tail_point(1 - share, degrees), degrees + 2)


def _distance() -> Column:
    """Squared Mahalanobis distance of x0.. from mean[], by the symmetric inverse[]."""
    d = [F.col(f"x{i}") - F.col("mean")[i] for i in range(D)]
    terms = [d[i] * d[j] * F.col("inverse")[i * D + j] * (1 if i == j else 2) for i in range(D) for j in range(i, D)]
    return sum(terms[1:], terms[0])


_PAIRS = [(i, j) for i in range(D) for j in range(i, D)]
_FOUND = "cell string, start int, mean array<double>, inverse array<double>, logdet double"


def _symmetric(upper: list[float]) -> np.ndarray:
    out = np.zeros((D, D))
    for (i, j), v in zip(_PAIRS, upper, strict=True):
        out[i, j] = out[j, i] = v
    return out


def _row(cell: str, start: int, mean: np.ndarray, cov: np.ndarray) -> tuple:
    """With the floor on the diagonal, so every covariance has an inverse."""
    cov = cov + np.eye(D) * FLOOR**2
    return cell, start, mean.tolist(), np.linalg.inv(cov).ravel().tolist(), float(np.linalg.slogdet(cov)[1])


def _estimates(moments: DataFrame, factor: float) -> DataFrame:
    """_FOUND from sums: (cell, start, n, s1, s2)."""

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.itertuples(index=False):
                mean = np.array(row.s1) / row.n
                out.append(_row(row.cell, row.start, mean, (_symmetric(np.array(row.s2) / row.n) - np.outer(mean, mean)) * factor))
            yield pd.DataFrame(out, columns=["cell", "start", "mean", "inverse", "logdet"])

    return moments.mapInPandas(run, _FOUND)


def _sums(weight: Column) -> list[Column]:
    x = [F.col(f"x{i}") for i in range(D)]
    return [F.sum(weight).alias("n"), F.array(*[F.sum(weight * v) for v in x]).alias("s1"), F.array(*[F.sum(weight * x[i] * x[j]) for i, j in _PAIRS]).alias("s2")]


def _starts(rows: DataFrame) -> DataFrame:
    """_FOUND of the three starts of each cell."""
    order = Window.partitionBy("cell", "i").orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    long = rows.select("cell", F.posexplode(F.array(*[F.col(f"x{i}") for i in range(D)])).alias("i", "x"))
    bins = long.groupBy("cell", "i", F.floor(F.col("x") * 64).alias("bin")).count()
    bins = bins.withColumn("below", F.sum("count").over(order)).withColumn("all", F.sum("count").over(Window.partitionBy("cell", "i")))
    at = lambda q: F.min(F.when(F.col("below") >= q * F.col("all"), (F.col("bin") + 0.5) / 64))
    middle = bins.groupBy("cell", "i").agg(at(0.5).alias("mid"), ((at(0.75) - at(0.25)) / 1.349).alias("scale"))
    first = stored(middle.groupBy("cell").agg(*[F.max(F.when(F.col("i") == i, F.col(c))).alias(f"{c}{i}") for i in range(D) for c in ("mid", "scale")]), "medians")
    z = [(F.col(f"x{i}") - F.col(f"mid{i}")) / F.sqrt(F.pow(F.col(f"scale{i}"), 2) + FLOOR**2) for i in range(D)]
    away = rows.join(checked(first, 10_000), "cell").select("cell", *[F.tanh(c).alias(f"t{i}") for i, c in enumerate(z)], *[c.alias(f"z{i}") for i, c in enumerate(z)])
    length = sum((F.col(f"z{i}") * F.col(f"z{i}") for i in range(1, D)), F.col("z0") * F.col("z0")) + 1e-12
    both = away.groupBy("cell").agg(F.count("*").cast("double").alias("n"), F.array(*[F.sum(F.col(f"z{i}") * F.col(f"z{j}") / length) for i, j in _PAIRS]).alias("signs"),
                                    F.array(*[F.sum(f"t{i}") for i in range(D)]).alias("t1"), F.array(*[F.sum(F.col(f"t{i}") * F.col(f"t{j}")) for i, j in _PAIRS]).alias("t2"))

    def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
        for frame in frames:
            out = []
            for row in frame.to_dict("records"):
                mid, scale = (np.array([row[f"{c}{i}"] for i in range(D)]) for c in ("mid", "scale"))
                mean = np.array(row["t1"]) / row["n"]
                squashed = _symmetric(np.array(row["t2"]) / row["n"]) - np.outer(mean, mean)
                spread = np.sqrt(np.maximum(np.diag(squashed), 1e-12))
                for start, shape in enumerate((np.eye(D), _symmetric(np.array(row["signs"]) / row["n"]) * D, squashed / np.outer(spread, spread))):
                    out.append(_row(row["cell"], start, mid, shape * np.outer(scale, scale)))
            yield pd.DataFrame(out, columns=["cell", "start", "mean", "inverse", "logdet"])

    return stored(both.join(first, "cell").mapInPandas(run, _FOUND), "cells")


def _step(rows: DataFrame, cells: DataFrame, share: float) -> DataFrame:
    """cells after one step: the nearest share of each cell's rows by the present estimate makes the next.

    Distances are compared on a log scale of 40 bins a factor of e, the same on any partitioning; of the last bin each row
    counts as the part of it that is needed, so the share is kept exactly.
    """
    key = ["cell", "start"]
    placed = rows.join(checked(cells.drop("logdet"), 10_000), "cell").select("*", F.floor(F.log(_distance() + 1e-6) * 40).alias("bin"))
    up = Window.partitionBy(*key).orderBy("bin").rowsBetween(Window.unboundedPreceding, 0)
    count = placed.groupBy(*key, "bin").count().withColumn("below", F.sum("count").over(up)).withColumn("want", share * F.sum("count").over(Window.partitionBy(*key)))
    last = count.where(F.col("below") >= F.col("want")).groupBy(*key).agg(F.min(F.struct("bin", ((F.col("want") - F.col("below") + F.col("count")) / F.col("count")).alias("part"))).alias("last"))
    inner = placed.join(checked(stored(last, "limits"), 10_000), key).where(F.col("bin") <= F.col("last.bin"))
    weight = F.when(F.col("bin") < F.col("last.bin"), 1.0).otherwise(F.col("last.part"))
    return stored(_estimates(inner.groupBy(*key).agg(*_sums(weight)), consistency(share)), "cells")


def estimate(rows: DataFrame, share: float = SHARE, first_steps: int = FIRST_STEPS, more_steps: int = MORE_STEPS, weighed: float | None = WEIGHED) -> DataFrame:
    """_FOUND of each cell of rows (cell, x0..); without weighed, of the nearest share of its rows alone."""
    cells = _starts(rows)
    for _ in range(first_steps):
        cells = _step(rows, cells, share)
    cells = stored(cells.groupBy("cell").agg(F.min_by(F.struct("start", "mean", "inverse", "logdet"), F.struct("logdet", "start")).alias("best")).select("cell", "best.*"), "cells")
    live, done = cells, []
    for _ in range(more_steps):
        old = live.select("cell", F.col("logdet").alias("was"))
        live = _step(rows.join(checked(live.select("cell"), 10_000), "cell", "left_semi"), live, share)
        moved = stored(live.join(old, "cell").withColumn("moves", F.abs(F.col("logdet") - F.col("was")) >= SETTLED).drop("was"), "cells")
        done.append(moved.where("not moves").drop("moves"))
        live = moved.where("moves").drop("moves")
        if live.isEmpty():
            break
    for part in done:
        live = live.unionByName(part)
    cells = stored(live, "cells") if done else live
    if weighed is None:
        return cells
    near = rows.join(checked(cells.drop("logdet"), 10_000), "cell").where(_distance() <= chi2_tail_point(1 - weighed, D))
    again = stored(_estimates(near.groupBy("cell", "start").agg(*_sums(F.lit(1.0))), consistency(weighed)), "cells")
    return again.unionByName(cells.join(again.select("cell"), "cell", "left_anti"))


def _part(name: str) -> Column:
    """A name within a cell's: null is no text and no pool's name."""
    return F.coalesce(F.concat(F.lit("="), F.col(name)), F.lit("null"))


def judged(docs: DataFrame, share: float = SHARE, tail: float = TAIL, cell_rows: int = CELL_ROWS) -> DataFrame:
    """doc_id, mark, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, distance and kept of every row.

    A null or empty text has no words and fails the base rules, which fail texts of fewer than 10 words or with over a
    fifth of them in repeated windows; only other rows shape the estimates. A null language or source is one of its own.
    distance is the squared Mahalanobis distance, null where the base rules failed. Repeated rows are judged alike and
    count as often as they come; an empty table gives no rows. mark tells rows of one id apart, see row_mark().
    """
    rows = stored(measured(docs), "statistics")
    sound = rows.where("not base_failed")
    counts = sound.groupBy("lang", "source").agg(F.count("*").alias("n"))
    pooled = F.sum(F.when(F.col("n") < cell_rows, F.col("n"))).over(Window.partitionBy("lang"))  # one row a cell
    name = F.when(F.col("n") >= cell_rows, F.concat_ws("\1", _part("lang"), _part("source"))).when(pooled >= cell_rows, F.concat_ws("\1", _part("lang"), F.lit("*"))).otherwise("*")
    cell = stored(counts.select(F.col("lang").alias("_lang"), F.col("source").alias("_source"), name.alias("cell")), "cell-of")
    of = lambda df: df.join(checked(cell, 10_000), F.col("lang").eqNullSafe(F.col("_lang")) & F.col("source").eqNullSafe(F.col("_source")), "left").drop("_lang", "_source")
    found = estimate(stored(of(sound).select("cell", *[f"x{i}" for i in range(D)]), "vectors"), share).select("cell", "mean", "inverse")
    placed = of(rows).join(checked(stored(found, "cells"), 10_000), "cell", "left")
    distance = F.when(~F.col("base_failed"), _distance())
    kept = ~F.col("base_failed") & F.coalesce(distance <= chi2_tail_point(tail, D), F.lit(True))
    return placed.select("doc_id", "mark", *COUNTS, "base_failed", distance.alias("distance"), kept.alias("kept"))


def drop_rejected(docs: DataFrame) -> DataFrame:
    """The rows of docs that are kept, with their own columns."""
    return without_rows(docs, stored(judged(docs).where("not kept").select("doc_id", "mark").distinct(), "rejected"), row_mark())


def op6(spark: SparkSession, sf_dir: str) -> DataFrame:
    return judged(documents(spark, sf_dir))
