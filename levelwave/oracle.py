"""DuckDB texts of the same results: graphs, distances by keyed recursion, and what is derived from them."""

from __future__ import annotations


def tagged(key: str, kind: int) -> str:
    return f"(CAST({key} AS BIGINT) * 16 + {kind})"


_LINES = "FROM lineitem"
_BOUGHT = "FROM lineitem JOIN orders ON o_orderkey = l_orderkey"
#: Directed edges of each graph, as SELECT src, dst.
EDGES = {
    "supply": f"SELECT {tagged('l_partkey', 0)} AS src, {tagged('l_suppkey', 1)} AS dst {_LINES}",
    "purchase": f"SELECT {tagged('l_partkey', 0)} AS src, {tagged('o_custkey', 2)} AS dst {_BOUGHT}",
    "basket": f"SELECT {tagged('l_partkey', 0)} AS src, {tagged('l_orderkey', 3)} AS dst {_LINES}",
    "sourcing": f"SELECT {tagged('o_custkey', 2)} AS src, {tagged('l_suppkey', 1)} AS dst {_BOUGHT}",
    "hierarchy": " UNION ALL ".join([
        f"SELECT {tagged('n_regionkey', 5)} AS src, {tagged('n_nationkey', 4)} AS dst FROM nation",
        f"SELECT {tagged('c_nationkey', 4)}, {tagged('c_custkey', 2)} FROM customer",
        f"SELECT {tagged('s_nationkey', 4)}, {tagged('s_suppkey', 1)} FROM supplier",
        f"SELECT {tagged('o_custkey', 2)}, {tagged('o_orderkey', 3)} FROM orders",
        f"SELECT {tagged('l_orderkey', 3)}, {tagged('l_partkey', 0)} FROM lineitem"]),
    "weblinks": f"""SELECT {tagged('page_id', 6)} AS src, {tagged("('0x' || substr(md5(href), 1, 14))", 7)} AS dst
        FROM (SELECT page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) AS href FROM pages)""",
    "trail": f"""SELECT src, dst FROM (
        WITH e AS (SELECT event_id, user_id, lead(event_id) OVER w AS next, row_number() OVER w AS rank FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)),
        f AS (SELECT user_id, event_id FROM e WHERE rank = 1)
        SELECT {tagged('event_id', 8)} AS src, {tagged('next', 8)} AS dst FROM e WHERE next IS NOT NULL
        UNION ALL SELECT {tagged('a.event_id', 8)}, {tagged('b.event_id', 8)} FROM f b JOIN f a ON a.user_id = b.user_id // 2 WHERE b.user_id > 0)""",
    "dialog": f"""SELECT {tagged('conv_id * 64 + turn', 12)} AS src, {tagged('conv_id * 64 + next', 12)} AS dst FROM (
        SELECT conv_id, turn, lead(turn) OVER (PARTITION BY conv_id ORDER BY turn) AS next FROM (SELECT DISTINCT conv_id, turn FROM conversations)) WHERE next IS NOT NULL""",
    "nearvec": f"""SELECT {tagged('vec_id', 11)} AS src, {tagged('other', 11)} AS dst FROM (
        SELECT vec_id, other, row_number() OVER (PARTITION BY vec_id ORDER BY c DESC, other) AS k FROM (
          SELECT a.vec_id, b.vec_id AS other, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS c
          FROM embeddings a JOIN embeddings b ON a.label = b.label AND a.vec_id <> b.vec_id)) WHERE k <= 8""",
    "copies": f"""SELECT {tagged('hub', 10)} AS src, {tagged('doc_id', 10)} AS dst FROM (
        SELECT doc_id, min(doc_id) OVER (PARTITION BY line) AS hub FROM (SELECT DISTINCT doc_id, line FROM (SELECT doc_id, trim(unnest(string_split(lower(text), chr(10))), ' ') AS line FROM documents) WHERE length(line) >= 40))
        WHERE hub < doc_id""",
    "nearvec_all": f"""SELECT {tagged('vec_id', 11)} AS src, {tagged('other', 11)} AS dst FROM (
        SELECT vec_id, other, row_number() OVER (PARTITION BY vec_id ORDER BY c DESC, other) AS k FROM (
          SELECT a.vec_id, b.vec_id AS other, round(list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]), 9) AS c
          FROM embeddings a JOIN embeddings b ON a.vec_id <> b.vec_id)) WHERE k <= 8""",
}
DIRECTED = {"hierarchy"}


def rmat_edges(scale: int, edge_factor: int, seed: int = 0) -> str:
    """Raw edges by the same integer arithmetic as the generator."""
    m = 1 << 31
    h0 = f"(CAST(i AS BIGINT) * 739982445 + b * 695872825 + 374761393 + {seed} * 1013904223) % {m}"
    h1 = f"(xor(h, h // 32768) * 739982445) % {m}"
    h2 = f"(xor(h, h // 4096) * 695872825) % {m}"
    return f"""SELECT sum(CASE WHEN x >= 78 THEN 1::BIGINT << b ELSE 0 END)::BIGINT AS src, sum(CASE WHEN x BETWEEN 59 AND 77 OR x >= 97 THEN 1::BIGINT << b ELSE 0 END)::BIGINT AS dst FROM (
        SELECT i, b, xor(h, h // 32768) % 102 AS x FROM (SELECT i, b, {h2} AS h FROM (SELECT i, b, {h1} AS h FROM (
        SELECT i, b, {h0} AS h FROM range({edge_factor << scale}) a(i), range({scale}) c(b))))) GROUP BY i"""


def arcs(graph: str, directed: bool | None = None, edges: str | None = None) -> str:
    """CTE text e and arcs, distinct and without loops."""
    directed = graph in DIRECTED if directed is None else directed
    both = "SELECT src, dst FROM e" if directed else "SELECT src, dst FROM e UNION ALL SELECT dst, src FROM e"
    return f"e AS MATERIALIZED ({edges or EDGES[graph]}), arcs AS MATERIALIZED (SELECT DISTINCT src, dst FROM ({both}) WHERE src <> dst)"


def with_levels(graph: str, source: int | str, directed: bool | None = None, edges: str | None = None, bound: int = 100_000, name: str = "lv", first: bool = True) -> str:
    """CTE text with the keyed distances <name>_d and the levels <name> (vertex, dist, parent). source: id or a scalar query."""
    text = f"{arcs(graph, directed, edges)}, " if first else ""
    return f"""{text}{name}_d(vertex, dist) USING KEY (vertex) AS (
        SELECT CAST({source} AS BIGINT) AS vertex, 0 AS dist
        UNION SELECT a.dst, min(r.dist) + 1 FROM {name}_d r JOIN arcs a ON a.src = r.vertex
          LEFT JOIN recurring.{name}_d k ON k.vertex = a.dst WHERE k.vertex IS NULL AND r.dist < {bound} GROUP BY a.dst),
      {name} AS MATERIALIZED (SELECT d.vertex, d.dist, coalesce(max(u.vertex), d.vertex) AS parent FROM {name}_d d
        LEFT JOIN arcs a ON a.dst = d.vertex LEFT JOIN {name}_d u ON u.vertex = a.src AND u.dist = d.dist - 1 GROUP BY d.vertex, d.dist)"""


def levels(graph: str, source: int | str, **options: object) -> str:
    return f"WITH RECURSIVE {with_levels(graph, source, **options)} SELECT vertex, dist, parent FROM lv"


def shuffled(vertex: str, seed: int = 0) -> str:
    """The hash of an id by the generator's arithmetic."""
    m = 1 << 31
    h0 = f"((({vertex}) % {m}) * 739982445 + (({vertex}) // {m}) * 695872825 + 374761393 + {seed} * 1013904223) % {m}"
    h1 = f"((xor({h0}, ({h0}) // 32768)) * 739982445) % {m}"
    h2 = f"((xor({h1}, ({h1}) // 4096)) * 695872825) % {m}"
    return f"xor({h2}, ({h2}) // 32768)"


def named(name: str) -> str:
    """The edges of a graph of the experiments: one of the tables, or rmat:scale or rmat:scale:edge_factor."""
    if not name.startswith("rmat:"):
        return EDGES[name]
    scale, factor = [*map(int, name.split(":")[1:]), 16][:2]
    return rmat_edges(scale, factor)


def component_rows(name: str = "c") -> str:
    """CTE text (vertex, component) over arcs."""
    return f"""{name}(vertex, component) USING KEY (vertex) AS (
        SELECT DISTINCT src AS vertex, src AS component FROM arcs
        UNION SELECT a.dst, min({name}.component) FROM {name} JOIN arcs a ON a.src = {name}.vertex JOIN recurring.{name} k ON k.vertex = a.dst
          WHERE {name}.component < k.component GROUP BY a.dst)"""


def many(name: str, k: int = 16) -> str:
    """WITH text: arcs of a graph, its component c, k sources s of the largest one, and lm (source, vertex, dist) of all."""
    return f"""WITH RECURSIVE {arcs("", False, named(name))}, {component_rows()},
      top AS (SELECT component FROM c GROUP BY component ORDER BY count(*) DESC, component LIMIT 1),
      s AS MATERIALIZED (SELECT vertex AS source FROM c JOIN top USING (component) ORDER BY {shuffled("vertex")}, vertex LIMIT {k}),
      lm(source, vertex, dist) USING KEY (source, vertex) AS (SELECT source, source AS vertex, 0 AS dist FROM s
        UNION SELECT r.source, a.dst, min(r.dist) + 1 FROM lm r JOIN arcs a ON a.src = r.vertex
          LEFT JOIN recurring.lm k ON k.source = r.source AND k.vertex = a.dst WHERE k.vertex IS NULL GROUP BY r.source, a.dst)"""


def components(graph: str) -> str:
    """Least vertex of each component, by keyed recursion over labels."""
    return f"WITH RECURSIVE {arcs(graph)}, {component_rows()}"
