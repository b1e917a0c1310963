"""SQL for DuckDB that gives the same answers as the queries, from the same tables."""

from __future__ import annotations

LONG = {
    "w1": "SELECT DISTINCT l_orderkey AS tid, p_brand AS item FROM lineitem JOIN part ON l_partkey = p_partkey",
    "w2": "SELECT DISTINCT o_custkey AS tid, p_brand AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey JOIN part ON l_partkey = p_partkey",
    "w3": "SELECT DISTINCT l_partkey AS tid, CAST(l_suppkey AS VARCHAR) AS item FROM lineitem",
    "w4": "SELECT DISTINCT o_custkey AS tid, CAST(l_suppkey AS VARCHAR) AS item FROM lineitem JOIN orders ON l_orderkey = o_orderkey",
    "w5": "SELECT DISTINCT tid, item FROM (SELECT doc_id AS tid, unnest(string_split_regex(lower(text), '[^a-z]+')) AS item FROM documents) WHERE item <> ''",
    "w6": "SELECT DISTINCT user_id * 100000 + date_diff('day', DATE '1970-01-01', CAST(ts AS DATE)) AS tid, event_type AS item FROM events",
    "w7": """SELECT tid, unnest([concat('flag=', l_returnflag), concat('status=', l_linestatus), concat('qty=', CAST(floor(l_quantity / 10) AS INTEGER)), concat('disc=', CAST(round(l_discount * 100) AS INTEGER)),
             concat('tax=', CAST(round(l_tax * 100) AS INTEGER)), concat('year=', year(l_shipdate))]) AS item FROM (SELECT row_number() OVER () AS tid, * FROM lineitem)""",
    "w8": "SELECT DISTINCT page_id AS tid, lower(unnest(regexp_extract_all(html, '<([a-zA-Z][a-zA-Z0-9]*)', 1))) AS item FROM pages",
    "w9": "SELECT DISTINCT tid, item FROM (SELECT conv_id AS tid, unnest(string_split_regex(lower(text), '[^a-z]+')) AS item FROM conversations) WHERE item <> ''",
    "w10": "SELECT vec_id AS tid, concat('d', i - 1) AS item FROM (SELECT vec_id, unnest(embedding) AS v, generate_subscripts(embedding, 1) AS i FROM embeddings) WHERE v > 0.1",
}
#: Baskets of each workload: those with items, or all source rows.
TOTAL = {w: "SELECT count(DISTINCT tid) FROM long" for w in LONG} | {"w5": "SELECT count(*) FROM documents", "w7": "SELECT count(*) FROM lineitem", "w8": "SELECT count(*) FROM pages", "w10": "SELECT count(*) FROM embeddings"}


def base(w: str, share: float) -> str:
    """long(tid, item), mc(n, c), single(item, tids), ord(item, item_rank, item_count)."""
    return f"""long AS MATERIALIZED ({LONG[w]}),
mc AS (SELECT n, greatest(1, CAST(ceil({share} * n - 1e-9) AS BIGINT)) AS c FROM (SELECT ({TOTAL[w]}) AS n)),
single AS (SELECT item, list(tid ORDER BY tid) AS tids FROM long GROUP BY item HAVING count(*) >= (SELECT c FROM mc)),
ord AS MATERIALIZED (SELECT item, CAST(row_number() OVER (ORDER BY len(tids) DESC, item) AS INTEGER) AS item_rank, CAST(len(tids) AS BIGINT) AS item_count FROM single),
rk AS MATERIALIZED (SELECT tid, item_rank AS r FROM long JOIN ord USING (item)),
ranked AS MATERIALIZED (SELECT tid, list(r ORDER BY r) AS items FROM rk GROUP BY tid)"""


def fi_cte(w: str, share: float, max_len: int | None = None) -> str:
    stop = f" AND f.size < {max_len}" if max_len else ""
    return f"""WITH RECURSIVE {base(w, share)},
f AS (SELECT item AS itemset, item AS last, 1 AS size, tids FROM single
  UNION ALL SELECT concat(f.itemset, '|', s.item), s.item, f.size + 1, list_intersect(f.tids, s.tids) FROM f JOIN single s ON s.item > f.last
  WHERE len(list_intersect(f.tids, s.tids)) >= (SELECT c FROM mc){stop}),
fi AS (SELECT itemset, CAST(size AS INTEGER) AS size, CAST(len(tids) AS BIGINT) AS support_count FROM f)"""


def mine(w: str, share: float, max_len: int | None = None) -> str:
    return fi_cte(w, share, max_len) + " SELECT * FROM fi"


def with_base(w: str, share: float, rest: str) -> str:
    return f"WITH {base(w, share)} {rest}"


PAIRS = "pairs AS MATERIALIZED (SELECT b.r AS hi, a.r AS lo, count(*) AS pair_count FROM rk a JOIN rk b ON a.tid = b.tid AND a.r < b.r GROUP BY ALL)"
PREFIXES = "pre AS MATERIALIZED (SELECT tid, items, items[k] AS item_rank, k AS depth, array_to_string(items[1:k], ',') AS node FROM (SELECT tid, items, unnest(range(1, len(items) + 1)) AS k FROM ranked))"

NU = "SELECT item_rank, CAST(sum(n) OVER (ORDER BY item_rank) AS BIGINT) AS nu FROM (SELECT item_rank, count(DISTINCT node) AS n FROM {pre} GROUP BY item_rank)"
MU = "SELECT b.r AS item_rank, count(DISTINCT p.node) AS mu FROM rk b JOIN {pre} p ON p.tid = b.tid AND p.item_rank < b.r JOIN pairs ON pairs.hi = b.r AND pairs.lo = p.item_rank AND pairs.pair_count >= (SELECT c FROM mc) GROUP BY b.r"


def pilot(capacity: int) -> str:
    """used(prefixes of the pilot's rows), pil(n_used, nodes, n_total): rows by tid until the tree would pass the capacity."""
    return f"""fst AS (SELECT node, min(tid) AS k FROM pre GROUP BY node),
seen AS (SELECT k, sum(count(*)) OVER (ORDER BY k) AS nodes FROM fst GROUP BY k),
stop AS (SELECT coalesce((SELECT min(k) FROM seen WHERE nodes > {capacity}), 9223372036854775807) AS k),
used AS (SELECT p.* FROM pre p WHERE tid < (SELECT k FROM stop)),
pil AS (SELECT count(DISTINCT tid) AS n_used, count(DISTINCT node) AS nodes, (SELECT count(*) FROM ranked) AS n_total FROM used)"""


def groups(capacity: int) -> str:
    """grp(group_id, lo, hi, est): the prefix head, then items one after another while the sum of their trees fits."""
    return f"""{PREFIXES}, {PAIRS}, {pilot(capacity)}, nu AS ({NU.format(pre='used')}), mu AS ({MU.format(pre='used')}),
s AS MATERIALIZED (SELECT o.item_rank, coalesce(max(nu.nu) OVER (ORDER BY o.item_rank), 0) AS nu, coalesce(mu.mu, 0) AS mu, max(coalesce(mu.mu, 0)) OVER (ORDER BY o.item_rank) AS most
  FROM ord o LEFT JOIN nu USING (item_rank) LEFT JOIN mu USING (item_rank)),
sc AS MATERIALIZED (SELECT CAST(n_total AS DOUBLE) / n_used AS scale, nodes, coalesce((SELECT max(item_rank) FROM s WHERE (s.nu + s.most) * (CAST(n_total AS DOUBLE) / n_used) <= nodes), 0) AS head FROM pil),
walk AS (SELECT item_rank, item_rank AS lo, mu AS acc FROM s, sc WHERE item_rank = head + 1
  UNION ALL SELECT s.item_rank, CASE WHEN (acc + s.mu) * scale <= nodes THEN lo ELSE s.item_rank END, CASE WHEN (acc + s.mu) * scale <= nodes THEN acc + s.mu ELSE s.mu END
  FROM walk JOIN s ON s.item_rank = walk.item_rank + 1 CROSS JOIN sc),
grp AS MATERIALIZED (SELECT CAST(row_number() OVER (ORDER BY lo) - 1 AS BIGINT) AS group_id, CAST(lo AS INTEGER) AS lo, CAST(hi AS INTEGER) AS hi, est FROM (
  SELECT 1 AS lo, head AS hi, nu * scale AS est FROM s JOIN sc ON item_rank = head
  UNION ALL SELECT lo, max(item_rank) AS hi, max(acc) * max(scale) AS est FROM walk, sc GROUP BY lo))"""


#: Trees that tasks really make for the groups, whole: of several anchors from rows cut behind the last, of one from its frequent partners.
REAL = """member AS (SELECT DISTINCT group_id, lo, hi, tid FROM grp JOIN rk ON r BETWEEN lo AND hi),
fpairs AS (SELECT hi, lo, pair_count FROM pairs WHERE pair_count >= (SELECT c FROM mc)),
alone AS (SELECT group_id, list(b.r ORDER BY b.r) AS items FROM member m JOIN rk b ON b.tid = m.tid AND b.r < m.lo JOIN fpairs f ON f.hi = m.lo AND f.lo = b.r WHERE m.lo = m.hi GROUP BY group_id, m.tid),
real AS (SELECT group_id, count(DISTINCT node) AS n FROM member m JOIN pre p ON p.tid = m.tid AND p.item_rank <= m.hi WHERE m.lo < m.hi GROUP BY group_id
  UNION ALL SELECT group_id, count(DISTINCT array_to_string(items[1:k], ',')) FROM (SELECT group_id, items, unnest(range(1, len(items) + 1)) AS k FROM alone) GROUP BY group_id HAVING count(DISTINCT items[k]) > 1)"""

#: Groups after short circuits and pruning, and the distinct rows that go to them; a head of over half of the items is not sent.
SENT = """fpairs AS (SELECT hi, lo, pair_count FROM pairs WHERE pair_count >= (SELECT c FROM mc)),
inside AS (SELECT o.item_rank AS a, group_id, lo, hi FROM ord o JOIN grp ON o.item_rank BETWEEN lo AND hi),
partner AS (SELECT i.group_id, i.a, f.lo AS b FROM inside i JOIN fpairs f ON f.hi = i.a UNION ALL SELECT i.group_id, i.a, f.hi FROM inside i JOIN fpairs f ON f.lo = i.a AND f.hi <= i.hi),
stays AS (SELECT group_id, a FROM partner GROUP BY ALL HAVING count(*) > 1),
kept AS (SELECT group_id, min(g.lo) AS lo, count(*) AS anchors FROM stays JOIN grp g USING (group_id) GROUP BY group_id),
sends AS (SELECT group_id FROM kept WHERE NOT (lo = 1 AND 2 * anchors > (SELECT count(*) FROM ord))),
allowed AS (SELECT group_id, a AS r FROM stays UNION SELECT st.group_id, f.lo FROM stays st JOIN fpairs f ON f.hi = st.a JOIN kept k ON k.group_id = st.group_id AND f.lo < k.lo),
sent AS (SELECT DISTINCT group_id, items FROM (SELECT m.group_id, m.tid, list(rk.r ORDER BY rk.r) AS items FROM (SELECT DISTINCT st.group_id, tid FROM stays st JOIN sends USING (group_id) JOIN rk ON rk.r = st.a) m
  JOIN rk ON rk.tid = m.tid JOIN allowed w ON w.group_id = m.group_id AND w.r = rk.r GROUP BY m.group_id, m.tid))"""


def recursive(w: str, share: float, rest: str) -> str:
    return f"WITH RECURSIVE {base(w, share)} {rest}"


def ledger(w: str, share: float, capacity: int, block: int = 4096) -> str:
    body = f""", {groups(capacity)}, {SENT},
e AS (SELECT 'ranked' AS phase, (SELECT count(*) FROM ranked) AS n, (SELECT count(*) FROM rk) AS cells
  UNION ALL SELECT 'collapsed', count(*), sum(len(items)) FROM (SELECT DISTINCT items FROM ranked)
  UNION ALL SELECT 'pairs', count(*), 2 * count(*) FROM pairs
  UNION ALL SELECT 'pilot rows', count(*), sum(len(items)) FROM (SELECT DISTINCT items FROM used)
  UNION ALL SELECT 'head', 0, 0 FROM kept WHERE lo = 1 AND 2 * anchors > (SELECT count(*) FROM ord)
  UNION ALL SELECT 'projected', count(*), sum(len(items)) FROM sent)"""
    return recursive(w, share, f"{body} SELECT phase, CAST(n AS BIGINT) AS rows, CAST(cells AS BIGINT) AS cells, CAST(4 * cells AS BIGINT) AS bytes, CAST(ceil(4 * cells / {block}.0) AS BIGINT) AS blocks FROM e")


def fi_in(cells: str, share: float, w: str, n_of: str, mc_of: str) -> str:
    """Recursion over baskets in cells: frequent(cell, itemset, size) with a threshold of each cell's own. Items are those frequent in all."""
    return f"""dealt AS MATERIALIZED (SELECT {cells} AS cell, tid, item FROM long JOIN ord USING (item)),
own AS MATERIALIZED (SELECT cell, {mc_of} AS c FROM ({n_of})),
one AS MATERIALIZED (SELECT dealt.cell, item, list(tid ORDER BY tid) AS tids FROM dealt JOIN own USING (cell) GROUP BY dealt.cell, item, c HAVING count(*) >= c),
f AS (SELECT cell, item AS itemset, item AS last, 1 AS size, tids FROM one
  UNION ALL SELECT f.cell, concat(f.itemset, '|', o.item), o.item, f.size + 1, list_intersect(f.tids, o.tids) FROM f JOIN one o ON o.cell = f.cell AND o.item > f.last JOIN own ON own.cell = f.cell
  WHERE len(list_intersect(f.tids, o.tids)) >= own.c)"""


def partition_candidates(w: str, share: float, cells: int) -> str:
    """CTEs up to found(itemset, size): sets frequent in a cell of baskets at least, cells by tid modulo."""
    local = f"greatest(1, CAST(ceil(CAST((SELECT c FROM mc) AS DOUBLE) / (SELECT n FROM mc) * n - 1e-9) AS BIGINT))"
    return f"""{fi_in(f'tid % {cells}', share, w, f'SELECT tid % {cells} AS cell, count(*) AS n FROM (SELECT DISTINCT tid FROM long) GROUP BY ALL', local)},
found AS (SELECT itemset, max(size) AS size FROM f GROUP BY itemset)"""


def moved(w: str, share: float, capacity: int, cells: int) -> str:
    """workload, share, method, itemsets, moved_cells of the three methods."""
    n = f"(SELECT count(*) FROM ({mine(w, share)}))"
    head = f"SELECT '{w}' AS workload, CAST({share} AS DOUBLE) AS share"
    grouped = recursive(w, share, f", {groups(capacity)}, {SENT} SELECT coalesce(sum(len(items)), 0) FROM sent")
    per_item = with_base(w, share, "SELECT sum(len(items)) FROM (SELECT DISTINCT items[1:k] AS items FROM (SELECT items, unnest(range(1, len(items) + 1)) AS k FROM ranked))")
    part = recursive(w, share, f", {partition_candidates(w, share, cells)} SELECT sum(size) FROM found")
    return " UNION ALL ".join(f"{head}, '{m}' AS method, {n} AS itemsets, CAST(({q}) AS BIGINT) AS moved_cells" for m, q in (("grouped", grouped), ("per item", per_item), ("partitioned", part)))
