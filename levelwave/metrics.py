"""Measures: rates, times, communication volume, balance, storage, redundancy."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .graphs import Graph
from .layout import GridLayout, RowLayout
from .prep import degrees

RUNS = "graph string, method string, p int, threads int, source long, edges long, seconds double"


class TaskMeter:
    """What tasks did while the block ran: their seconds, those of writing to shuffles and waiting for them, and megabytes
    through shuffles. Read from the session's own record of its last stages (1000 by default), so nothing else may run
    meanwhile."""

    def __init__(self, spark: SparkSession):
        self.store, self.jvm = spark._jsc.sc().statusStore(), spark._jvm
        self.gateway = spark.sparkContext._gateway

    def _stages(self) -> list:
        none = self.jvm.java.util.ArrayList()
        stages = self.store.stageList(none, False, False, self.gateway.new_array(self.gateway.jvm.double, 0), none)
        return [stages.apply(i) for i in range(stages.size())]

    def __enter__(self) -> TaskMeter:
        self.last = max((s.stageId() for s in self._stages()), default=-1)
        return self

    def __exit__(self, *error: object) -> None:
        found = [s for s in self._stages() if s.stageId() > self.last]
        self.run_seconds = sum(s.executorRunTime() for s in found) / 1e3
        self.comm_seconds = sum(s.shuffleWriteTime() / 1e9 + s.shuffleFetchWaitTime() / 1e3 for s in found)
        self.megabytes = sum(s.shuffleReadBytes() + s.shuffleWriteBytes() for s in found) / 1e6


def edges_traversed(graph: Graph, levels: DataFrame) -> DataFrame:
    """One row: input edges in what was reached, over all searches; an undirected edge counts once though it is stored twice."""
    out = degrees(graph.arcs).join(levels.select("vertex"), "vertex").agg(F.coalesce(F.sum("degree"), F.lit(0)).alias("arcs"))
    return out.select((F.col("arcs") if graph.directed else F.expr("arcs div 2")).alias("edges"))


def teps(edges: float, seconds: float) -> float:
    """Traversed edges a second."""
    return edges / seconds


def mean_search_time(runs: DataFrame) -> DataFrame:
    """By graph, method, p and threads: searches, mean seconds, and edges a second over their mean time."""
    return runs.groupBy("graph", "method", "p", "threads").agg(F.count("*").alias("searches"), F.avg("seconds").alias("mean_seconds"), (F.avg("edges") / F.avg("seconds")).alias("teps"))


def speedup(runs: DataFrame, baseline: str) -> DataFrame:
    """(graph, method, p, ratio): the baseline's mean time over each method's, at equal p."""
    mean = mean_search_time(runs)
    base = mean.where(F.col("method") == baseline).select("graph", "p", F.col("mean_seconds").alias("base"))
    return mean.join(base, ["graph", "p"]).select("graph", "method", "p", (F.col("base") / F.col("mean_seconds")).alias("ratio"))


def volume_rows(graph: Graph, levels: DataFrame, layout: RowLayout) -> DataFrame:
    """By level: vertices, arcs scanned, candidates after senders combined theirs, and candidates that change owner."""
    at = levels.select(F.col("vertex").alias("src"), "dist")
    sent = graph.arcs.join(at, "src").groupBy("dist", layout.owner(F.col("src")).alias("sender"), "dst").agg(F.count("*").alias("n"))
    moved = sent.groupBy("dist").agg(F.sum("n").alias("scanned"), F.count("*").alias("candidates"), F.count(F.when(F.col("sender") != layout.owner(F.col("dst")), 1)).alias("shipped"))
    return _by_level(levels, moved, ["scanned", "candidates", "shipped"])


def volume_grid(graph: Graph, levels: DataFrame, layout: GridLayout) -> DataFrame:
    """By level: vertices, arcs scanned, entries that cells get by the expand from other cells, candidates of all cells,
    and candidates that the fold moves to another cell."""
    at = levels.select(F.col("vertex").alias("src"), "dist")
    cells = graph.arcs.join(at, "src").groupBy("dist", layout.cell(F.col("src"), F.col("dst")).alias("cell"), "dst").agg(F.count("*").alias("n"))
    folded = cells.groupBy("dist").agg(F.sum("n").alias("scanned"), F.count("*").alias("candidates"), F.count(F.when(F.col("cell") != layout.owner(F.col("dst")), 1)).alias("folded"))
    # All p_r cells of a grid column get each entry; one of them may be its owner.
    own = (layout.owner(F.col("vertex")) % layout.p_c == layout.column(F.col("vertex"))).cast("long")
    expanded = levels.groupBy("dist").agg(F.sum(F.lit(layout.p_r) - own).alias("expanded"))
    return _by_level(levels, folded.join(expanded, "dist", "full_outer"), ["scanned", "expanded", "candidates", "folded"])


def _by_level(levels: DataFrame, counts: DataFrame, names: list[str]) -> DataFrame:
    out = levels.groupBy("dist").agg(F.count("*").alias("vertices")).join(counts, "dist", "left")
    return out.select("dist", "vertices", *[F.coalesce(F.col(c), F.lit(0)).cast("long").alias(c) for c in names])


def phase_split(volume: DataFrame) -> DataFrame:
    """One row: entries expanded and folded over all levels, and each one's share."""
    both = volume.agg(F.sum("expanded").alias("expanded"), F.sum("folded").alias("folded"))
    total = F.col("expanded") + F.col("folded")
    return both.select("expanded", "folded", F.round(F.col("expanded") / total, 6).alias("expand_share"), F.round(F.col("folded") / total, 6).alias("fold_share"))


def comm_share(trace: DataFrame, words_per_second: float) -> DataFrame:
    """One row: seconds that the counted words take at a rate, and their share of all seconds (exchange included)."""
    words = F.coalesce(F.col("shipped"), F.lit(0)) + F.coalesce(F.col("expanded"), F.lit(0)) + F.coalesce(F.col("folded"), F.lit(0))
    return trace.agg(F.sum(words).alias("words"), F.sum("seconds").alias("seconds")).select("words", "seconds", (F.col("words") / words_per_second).alias("comm_seconds"), (F.col("words") / words_per_second / F.col("seconds")).alias("comm_share"))


def imbalance(rows: DataFrame, owner: str, places: int) -> DataFrame:
    """One row: rows, places that have some, the greatest load, and that over the mean of all places."""
    loads = rows.groupBy(owner).agg(F.count("*").alias("load"))
    return loads.agg(F.sum("load").alias("rows"), F.count("*").alias("active"), F.max("load").alias("most")).select("rows", "active", "most", F.round(F.col("most") * places / F.col("rows"), 6).alias("imbalance"))


def merged_per_owner(graph: Graph, levels: DataFrame, layout: GridLayout) -> DataFrame:
    """(owner) of every candidate that an owner has to merge over the whole traversal."""
    at = levels.select(F.col("vertex").alias("src"), "dist")
    cells = graph.arcs.join(at, "src").select("dist", layout.cell(F.col("src"), F.col("dst")).alias("cell"), "dst").distinct()
    return cells.select(layout.owner(F.col("dst")).alias("owner"))


def edge_cut(graph: Graph, layout: RowLayout) -> DataFrame:
    """One row: arcs, and arcs whose ends have different owners."""
    return graph.arcs.agg(F.count("*").alias("arcs"), F.count(F.when(layout.owner(F.col("src")) != layout.owner(F.col("dst")), 1)).alias("cut"))


def storage_words(kind: str, n: int, m: int, p_r: int, p_c: int) -> int:
    """Words over all places: csr (rows), csr_grid, dcsc, heap, spa."""
    return {"csr": n + m, "csr_grid": n * p_r + m, "dcsc": m, "heap": m, "spa": n * p_c}[kind]


def spa_bytes_per_core(n: int, p_c: int) -> float:
    return 9 * n / p_c


def storage_table(spark: SparkSession, points: list[tuple[int, int, int, int]]) -> DataFrame:
    """(n, m, p_r, p_c, kind, words) of each point and kind."""
    rows = [(*pt, kind, storage_words(kind, *pt)) for pt in points for kind in ("csr", "csr_grid", "dcsc", "heap", "spa")]
    return spark.createDataFrame(rows, "n long, m long, p_r int, p_c int, kind string, words long")


def storage_measured(graph: Graph, layout: GridLayout) -> DataFrame:
    """(kind, words) of the index arrays as packed: pointers and row numbers of dcsc and of csr with all pointers, on the cells."""
    from .grid import pack_csr_cells, pack_dcsc

    size = lambda *names: sum((F.size(n) for n in names[1:]), F.size(names[0])).cast("long")
    # The parts of a cell have an end pointer each, the cell one; columns past the range are not of the form.
    one = lambda words: F.sum(words) - F.count("*") + 1
    packs = (("dcsc", pack_dcsc(graph.arcs, layout), ("jc", "cp", "ir")), ("csr", pack_csr_cells(graph.arcs, layout), ("cp", "ir")))
    both = [df.groupBy("cell").agg(one(size(*names)).alias("words")).select(F.lit(kind).alias("kind"), "words") for kind, df, names in packs]
    return both[0].unionAll(both[1]).groupBy("kind").agg(F.sum("words").alias("words"))


def scaling_table(runs: DataFrame) -> DataFrame:
    """runs (graph, method, p, mean_seconds) with speedup, over the fewest places of the method, and efficiency at p places."""
    least = runs.groupBy("graph", "method").agg(F.min_by(F.struct(F.col("p").alias("p0"), F.col("mean_seconds").alias("s0")), "p").alias("first"))
    out = runs.join(least, ["graph", "method"]).withColumn("speedup", F.col("first.s0") / F.col("mean_seconds"))
    return out.select("graph", "method", "p", "mean_seconds", "speedup", (F.col("speedup") * F.col("first.p0") / F.col("p")).alias("efficiency"))


def kernel_ratio(crossover: DataFrame) -> DataFrame:
    """(p_c, ratio): heap time over accumulator time of the local merges, from (p_c, heap_seconds, spa_seconds)."""
    return crossover.select("p_c", (F.col("heap_seconds") / F.col("spa_seconds")).alias("ratio"))


def working_set(layout: RowLayout | GridLayout, n: int) -> dict[str, int]:
    """Words over which random reads spread: distances or vectors of a place."""
    if isinstance(layout, RowLayout):
        return {"distances": n // layout.p}
    return {"input": n // layout.p_c, "output": n // layout.p_r}


def redundant_rate(counts: DataFrame) -> DataFrame:
    """From (pushes, redundant): the share of pushes that came again."""
    return counts.select("pushes", "redundant", F.round(F.col("redundant") / F.col("pushes"), 6).alias("rate"))


def degree_topk(graph: Graph, k: int) -> DataFrame:
    return degrees(graph.arcs).orderBy(F.desc("degree"), "vertex").limit(k)
