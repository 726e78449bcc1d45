"""DuckDB SQL with the same result as iterative queries: the same sweeps as chained table expressions."""

from __future__ import annotations

POINTS = {
    "exact": """SELECT concat_ws('-', l_orderkey, l_linenumber, l_partkey, l_suppkey, CAST(l_extendedprice AS VARCHAR)) AS pid, CAST(round(l_quantity) AS BIGINT) AS x0,
      CAST(round(l_extendedprice / 1000) AS BIGINT) AS x1, CAST(round(l_discount * 100) AS BIGINT) AS x2, CAST(round(l_tax * 100) AS BIGINT) AS x3, l_linenumber AS line, l_orderkey AS okey FROM lineitem""",
}
POINTS["started"] = f"SELECT pid, x0, x1, x2, x3, CAST((okey + line) % {{k}} AS INT) AS start FROM ({POINTS['exact']})"
POINTS["anchored"] = f"SELECT pid, x0 + 1000 * (line % 4) AS x0, x1 + 1000 * (line % 4) AS x1, x2 + 1000 * (line % 4) AS x2, x3 + 1000 * (line % 4) AS x3, CAST(line % 4 AS INT) AS truth FROM ({POINTS['exact']})"
POINTS["events"] = """SELECT user_id AS pid, count(*) AS x0, count(DISTINCT event_type) AS x1, CAST(sum(CAST(round(value * 100) AS BIGINT)) AS BIGINT) AS x2,
  CAST(count(*) FILTER (event_type = 'purchase') AS BIGINT) AS x3, CAST(user_id % {k} AS INT) AS start FROM events GROUP BY user_id"""
POINTS["documents"] = r"""SELECT doc_id AS pid, length(text) AS x0, length(text) - length(replace(text, ' ', '')) AS x1, length(text) - length(replace(text, chr(10), '')) AS x2,
  length(text) - length(regexp_replace(text, '[0-9]', '', 'g')) AS x3, CAST(doc_id % {k} AS INT) AS start FROM documents"""
POINTS["customers"] = """SELECT c_custkey AS pid, coalesce(n, 0) AS x0, CAST(coalesce(floor(paid / 1000), 0) AS BIGINT) AS x1, CAST(floor(c_acctbal / 100) AS BIGINT) AS x2, CAST(c_custkey % {k} AS INT) AS start
  FROM customer LEFT JOIN (SELECT o_custkey, count(*) AS n, CAST(sum(CAST(round(o_totalprice) AS BIGINT)) AS BIGINT) AS paid FROM orders GROUP BY 1) ON o_custkey = c_custkey"""


def embedding_points(d: int) -> str:
    xs = ", ".join(f"CAST(round(CAST(embedding[{j + 1}] AS DOUBLE) * 1048576) AS BIGINT) AS x{j}" for j in range(d))
    return f"SELECT vec_id AS pid, {xs}, CAST(vec_id % {{k}} AS INT) AS start FROM embeddings"


def kmeans_chain(points: str, d: int, k: int, sweeps: int, tie: str = "stay") -> str:
    """WITH clause whose last tables are a<sweeps> (pid, x.., c) and m<sweeps> (m, n, s..)."""
    xs = ", ".join(f"x{j}" for j in range(d))
    sums = ", ".join(f"CAST(sum(x{j}) AS DOUBLE) AS s{j}" for j in range(d))
    out = [f"a0 AS MATERIALIZED (SELECT pid, {xs}, start AS c FROM ({points.format(k=k)}))", f"m0 AS MATERIALIZED (SELECT c AS m, count(*) AS n, {sums} FROM a0 GROUP BY c)"]
    for t in range(1, sweeps + 1):
        one = ", ".join(f"max(CASE WHEN m = {m} THEN s{j} / n END) AS q{m}_{j}" for m in range(k) for j in range(d))
        out.append(f"w{t - 1} AS MATERIALIZED (SELECT {one} FROM m{t - 1})")
        ds = ", ".join("(" + " + ".join(f"(x{j} - q{m}_{j}) * (x{j} - q{m}_{j})" for j in range(d)) + f") AS d{m}" for m in range(k))
        low = "least(" + ", ".join(f"d{m}" for m in range(k)) + ")"
        order = range(k) if tie == "stay" else range(k - 1, -1, -1)
        pick = "CASE " + " ".join(f"WHEN d{m} = {low} THEN {m}" for m in order) + " END"
        own = "CASE c " + " ".join(f"WHEN {m} THEN d{m}" for m in range(k)) + " END"
        best = f"CASE WHEN {low} < {own} THEN {pick} ELSE c END" if tie == "stay" else pick
        out.append(f"a{t} AS MATERIALIZED (SELECT pid, {xs}, CAST({best} AS INT) AS c FROM (SELECT a{t - 1}.*, {ds} FROM a{t - 1}, w{t - 1}))")
        out.append(f"m{t} AS MATERIALIZED (SELECT c AS m, count(*) AS n, {sums} FROM a{t} GROUP BY c)")
    return "WITH " + ",\n".join(out)


def kmeans_centres(points: str, d: int, k: int, sweeps: int, tie: str = "stay") -> str:
    cs = ", ".join(f"round(s{j} / n, 6) AS c{j}" for j in range(d))
    return f"{kmeans_chain(points, d, k, sweeps, tie)}\nSELECT m, CAST(n AS BIGINT) AS size, {cs} FROM m{sweeps}"


GRAPHS = {
    "trade": "SELECT DISTINCT o_custkey * 2 AS u, l_suppkey * 2 + 1 AS v FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "handover": "SELECT DISTINCT u, v FROM (SELECT l_suppkey AS u, lead(l_suppkey) OVER (PARTITION BY l_partkey ORDER BY l_shipdate, l_orderkey, l_linenumber, l_suppkey, l_extendedprice) AS v FROM lineitem) WHERE v IS NOT NULL AND u <> v",
    "transitions": "SELECT DISTINCT u, v FROM (SELECT CAST(floor(value) AS BIGINT) % 50 AS u, lead(CAST(floor(value) AS BIGINT) % 50) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS v FROM events) WHERE v IS NOT NULL",
    "names": """SELECT DISTINCT CAST(page_id AS VARCHAR) AS a, unnest(regexp_extract_all(html, 'href="(/[^"]*)"', 1)) AS b FROM pages""",
}
GRAPHS["pages"] = f"""SELECT p.id AS u, q.id AS v FROM ({GRAPHS["names"]}) e
  JOIN (SELECT name, row_number() OVER (ORDER BY name) AS id FROM (SELECT a AS name FROM ({GRAPHS["names"]}) UNION SELECT b FROM ({GRAPHS["names"]}))) p ON p.name = e.a
  JOIN (SELECT name, row_number() OVER (ORDER BY name) AS id FROM (SELECT a AS name FROM ({GRAPHS["names"]}) UNION SELECT b FROM ({GRAPHS["names"]}))) q ON q.name = e.b"""


def _graph(graph: str) -> list[str]:
    return [
        f"e AS MATERIALIZED ({GRAPHS[graph]})", "v AS MATERIALIZED (SELECT u AS id FROM e UNION SELECT v FROM e)", "n AS MATERIALIZED (SELECT count(*) AS n FROM v)",
        "g AS MATERIALIZED (SELECT id, dout FROM v LEFT JOIN (SELECT u, count(*) AS dout FROM e GROUP BY u) ON u = id)",
    ]


def _step(prev: str, d: float, fold: bool = True) -> str:
    """Sum over in-edges, and the folded part, of column x of the previous table."""
    lone = f"(SELECT coalesce(sum(CASE WHEN dout IS NULL THEN x END), 0) FROM {prev})"
    folded = f" + ({lone} - CASE WHEN dout IS NULL THEN x ELSE 0 END) / greatest(1, (SELECT n FROM n) - 1)" if fold else ""
    return f"SELECT p.id, p.dout, {d} * (coalesce(s, 0){folded}) AS x FROM {prev} p LEFT JOIN (SELECT e.v, sum(x / dout) AS s FROM e JOIN {prev} q ON q.id = e.u GROUP BY e.v) a ON a.v = p.id"


def rank_delta(graph: str, sweeps: int, d: float = 0.85, digits: int = 9, select: str = "SELECT id, round(sum(x), {digits}) AS pr FROM t GROUP BY id") -> str:
    """Ranks after so many sweeps of pending differences."""
    out = [*_graph(graph), f"t0 AS MATERIALIZED (SELECT id, dout, (1 - {d}) / n AS x FROM g, n)"]
    out += [f"t{i} AS MATERIALIZED ({_step(f't{i - 1}', d)})" for i in range(1, sweeps + 1)]
    out.append("t AS (" + " UNION ALL ".join(f"SELECT id, x, {i} AS sweep FROM t{i}" for i in range(sweeps + 1)) + ")")
    return "WITH " + ",\n".join(out) + "\n" + select.format(digits=digits)


def rank_classic(graph: str, sweeps: int, d: float = 0.85, digits: int = 9) -> str:
    out = [*_graph(graph), "t0 AS MATERIALIZED (SELECT id, dout, 1.0::DOUBLE / n AS x FROM g, n)"]
    out += [f"t{i} AS MATERIALIZED (SELECT id, dout, (1 - {d}) / (SELECT n FROM n) + x AS x FROM ({_step(f't{i - 1}', d)}))" for i in range(1, sweeps + 1)]
    return "WITH " + ",\n".join(out) + f"\nSELECT id, round(x, {digits}) AS pr FROM t{sweeps}"
