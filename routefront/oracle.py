"""SQL for DuckDB that gives the rows of the queries. Grid network, task sets, bounds and fronts as common table expressions."""

from __future__ import annotations

GRID = """
w0 AS (SELECT CAST(ceil(sqrt(count(*))) AS BIGINT) AS w, count(*) AS n FROM customer),
cu AS (SELECT c_custkey AS k, c_nationkey AS nation, c_mktsegment AS seg, CAST(floor(c_acctbal / 100) AS BIGINT) AS alt, w, n FROM customer, w0),
pr AS (SELECT a.k AS src, b.k AS dst, a.seg, a.alt AS alt1, b.alt AS alt2, b.nation, a.w FROM cu a JOIN cu b ON b.k = a.k + 1 WHERE (a.k + 1) % a.w <> 0
       UNION ALL SELECT a.k, b.k, a.seg, a.alt, b.alt, b.nation, a.w FROM cu a JOIN cu b ON b.k = a.k - 1 WHERE a.k % a.w <> 0
       UNION ALL SELECT a.k, b.k, a.seg, a.alt, b.alt, b.nation, a.w FROM cu a JOIN cu b ON b.k = a.k + a.w
       UNION ALL SELECT a.k, b.k, a.seg, a.alt, b.alt, b.nation, a.w FROM cu a JOIN cu b ON b.k = a.k - a.w),
e0 AS (SELECT *, 100 + (least(src, dst) * 7919 + greatest(src, dst) * 104729) % 151 AS c_distance FROM pr WHERE abs(src - dst) = 1 OR least(src, dst) % 3 <> 0 OR src % w = 0),
e1 AS (SELECT *, c_distance * 36 // CASE seg WHEN 'BUILDING' THEN 30 WHEN 'HOUSEHOLD' THEN 50 WHEN 'FURNITURE' THEN 70 WHEN 'MACHINERY' THEN 100 ELSE 130 END AS c_time FROM e0),
edges AS MATERIALIZED (SELECT src, dst, CAST(c_time AS BIGINT) AS c_time, CAST(c_distance AS BIGINT) AS c_distance, CAST(CASE WHEN nation % 3 = 0 THEN 1 ELSE 0 END AS BIGINT) AS c_crossings,
       CAST(c_time + CASE WHEN nation % 6 = 0 THEN 300 WHEN nation % 3 = 0 THEN 150 ELSE 0 END AS BIGINT) AS c_penalised, CAST(greatest(0, c_distance // 4 + alt2 - alt1) AS BIGINT) AS c_energy FROM e1)"""

TASKS = """tasks AS (SELECT 1 AS task_id, CAST(0 AS BIGINT) AS src, least(5, n - 1) AS dst FROM w0 UNION ALL SELECT 2, 0, n * 4 // 15 FROM w0 UNION ALL SELECT 3, 20 % n, n * 3 // 10 FROM w0)"""

LOCAL = """ends AS (SELECT k AS node FROM cu WHERE abs(k // w - w // 2) <= 4 AND abs(k % w - w // 2) <= 4 AND (k // w + k % w) % 3 = 0),
tasks AS (SELECT row_number() OVER (ORDER BY a.node, b.node) AS task_id, a.node AS src, b.node AS dst FROM ends a JOIN ends b ON a.node <> b.node)"""

WIDE = """tile AS (SELECT c_custkey, c_acctbal, ntile(10) OVER (ORDER BY c_custkey) AS t FROM customer),
ends AS (SELECT c_custkey AS node FROM (SELECT *, row_number() OVER (PARTITION BY t ORDER BY c_acctbal DESC, c_custkey) AS r FROM tile) WHERE r = 1),
tasks AS (SELECT row_number() OVER (ORDER BY a.node, b.node) AS task_id, a.node AS src, b.node AS dst FROM ends a JOIN ends b ON a.node <> b.node)"""

TRADE = """
tr AS (SELECT CAST(s_nationkey AS BIGINT) AS src, CAST(c_nationkey AS BIGINT) AS dst, CAST(floor(l_extendedprice * 100 / l_quantity) AS BIGINT) AS cents, abs(date_diff('day', CAST(o_orderdate AS DATE), CAST(l_shipdate AS DATE))) AS lag
       FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN customer ON o_custkey = c_custkey JOIN supplier ON l_suppkey = s_suppkey WHERE s_nationkey <> c_nationkey),
trade AS (SELECT src, dst, CAST(floor(sum(cents) / count(*)) AS BIGINT) AS c_price, CAST(floor(sum(lag) / count(*)) AS BIGINT) AS c_lag, CAST(10000 // count(*) AS BIGINT) AS c_rarity, CAST(1 AS BIGINT) AS c_hop FROM tr GROUP BY src, dst)"""

FLOW = """
fl AS (SELECT l_partkey AS src, lead(l_partkey) OVER o AS dst, CAST(floor(l_extendedprice) AS BIGINT) AS c_price, CAST(floor(l_quantity) AS BIGINT) AS c_quantity,
       abs(date_diff('day', CAST(l_shipdate AS DATE), CAST(lead(l_shipdate) OVER o AS DATE))) AS c_days FROM lineitem
       WINDOW o AS (PARTITION BY l_orderkey ORDER BY l_linenumber, l_partkey, l_suppkey, l_quantity, l_extendedprice, l_shipdate)),
flow AS (SELECT src, dst, c_price, c_quantity, c_days FROM (SELECT *, row_number() OVER (PARTITION BY src ORDER BY c_price, dst, c_quantity, c_days) AS r FROM fl WHERE dst IS NOT NULL AND dst <> src) WHERE r <= 3)"""


def _le(a: list[str], b: list[str]) -> str:
    return " AND ".join(f"{x} <= {y}" for x, y in zip(a, b, strict=True))


def dominated_by(a: list[str], b: list[str]) -> str:
    """a dominates b."""
    return f"({_le(a, b)} AND ({' OR '.join(f'{x} < {y}' for x, y in zip(a, b, strict=True))}))"


def single_bounds(i: int, d: int, backward: bool = True) -> str:
    """lb{i}(task_id, node, key, v0..): key = value * 10**8 + total of an optimal walk, v its cost vector."""
    start, frm, to = ("dst", "dst", "src") if backward else ("src", "src", "dst")
    vec = ", ".join(f"v{j}" for j in range(d))
    total = " + ".join(f"e.c{j}" for j in range(d))
    return f"""lb{i}(task_id, node, key, {vec}) USING KEY (task_id, node) AS (
  SELECT task_id, {start}, CAST(0 AS BIGINT), {", ".join("CAST(0 AS BIGINT)" for _ in range(d))} FROM tasks
  UNION
  SELECT x.task_id, x.node, min(x.nk), {", ".join(f"arg_min(x.n{j}, x.nk)" for j in range(d))} FROM (
    SELECT l.task_id, e.{to} AS node, l.key + e.c{i} * 100000000 + {total} AS nk, {", ".join(f"l.v{j} + e.c{j} AS n{j}" for j in range(d))} FROM lb{i} l JOIN ed e ON e.{frm} = l.node) x
  LEFT JOIN recurring.lb{i} r ON r.task_id = x.task_id AND r.node = x.node WHERE r.key IS NULL OR x.nk < r.key GROUP BY x.task_id, x.node)"""


def base(criteria: list[str], tasks: str = TASKS, where: str = "") -> str:
    cols = ", ".join(f"{c} AS c{i}" for i, c in enumerate(criteria))
    return f"WITH RECURSIVE {GRID}, {tasks}, ed AS MATERIALIZED (SELECT src, dst, {cols} FROM edges{where})"


def bounds(criteria: list[str], tasks: str = TASKS) -> str:
    """CTEs up to lb(task_id, node, b0..) and anchors(task_id, criterion, a0..)."""
    d = len(criteria)
    parts = [single_bounds(i, d) for i in range(d)]
    lb = f"lb AS MATERIALIZED (SELECT lb0.task_id, lb0.node, {', '.join(f'lb{i}.key // 100000000 AS b{i}' for i in range(d))} FROM lb0 {' '.join(f'JOIN lb{i} USING (task_id, node)' for i in range(1, d))})"
    anchors = "anchors AS MATERIALIZED (" + " UNION ALL ".join(f"SELECT t.task_id, {i} AS criterion, {', '.join(f'v{j} AS a{j}' for j in range(d))} FROM lb{i} l JOIN tasks t ON t.task_id = l.task_id AND t.src = l.node" for i in range(d)) + ")"
    return ", ".join([base(criteria, tasks), *parts, lb, anchors])


def front(criteria: list[str], tasks: str = TASKS) -> str:
    """CTEs up to front(task_id, c0..): distinct non-dominated vectors."""
    d = len(criteria)
    c = [f"c{i}" for i in range(d)]
    new = [f"l.c{i} + e.c{i}" for i in range(d)]
    reach = [f"l.c{i} + e.c{i} + b.b{i}" for i in range(d)]
    return f"""{bounds(criteria, tasks)}, lab(task_id, node, {", ".join(c)}) AS (
  SELECT task_id, src, {", ".join("CAST(0 AS BIGINT)" for _ in c)} FROM tasks
  UNION ALL
  (WITH cand AS (SELECT DISTINCT l.task_id, e.dst AS node, {", ".join(f"{x} AS c{i}" for i, x in enumerate(new))}
     FROM lab l JOIN tasks t ON t.task_id = l.task_id JOIN ed e ON e.src = l.node JOIN lb b ON b.task_id = l.task_id AND b.node = e.dst
     WHERE l.node <> t.dst AND e.dst <> t.src AND NOT EXISTS (SELECT 1 FROM anchors a WHERE a.task_id = l.task_id AND {dominated_by([f"a.a{i}" for i in range(d)], reach)}))
   SELECT * FROM cand x WHERE NOT EXISTS (SELECT 1 FROM cand o WHERE o.task_id = x.task_id AND o.node = x.node AND {dominated_by([f"o.{y}" for y in c], [f"x.{y}" for y in c])}))),
fin AS (SELECT DISTINCT l.task_id, {", ".join(f"l.{x}" for x in c)} FROM lab l JOIN tasks t ON t.task_id = l.task_id AND t.dst = l.node),
front AS MATERIALIZED (SELECT * FROM fin x WHERE NOT EXISTS (SELECT 1 FROM fin o WHERE o.task_id = x.task_id AND {dominated_by([f"o.{y}" for y in c], [f"x.{y}" for y in c])}))"""


def front_rows(criteria: list[str], tasks: str = TASKS) -> str:
    return f"{front(criteria, tasks)} SELECT CAST(task_id AS BIGINT) AS task_id, {', '.join(f'c{i} AS {c}' for i, c in enumerate(criteria))} FROM front"


def table_front(source: str, criteria: list[str], by: list[str], columns: str) -> str:
    on = " AND ".join([*(f"o.{b} IS NOT DISTINCT FROM x.{b}" for b in by), dominated_by([f"o.{c}" for c in criteria], [f"x.{c}" for c in criteria])])
    return f"WITH t AS ({source}) SELECT {columns} FROM t x WHERE NOT EXISTS (SELECT 1 FROM t o WHERE {on})"
