"""SQL of the graphs, of sequential placement and of the measures, for engines with recursive queries."""

from __future__ import annotations

import math

from ..functions.hashes import hashed_sql

T = {t: f"(SELECT count(*) FROM {t})" for t in ("orders", "part", "supplier", "customer", "events", "documents", "embeddings", "pages", "conversations")}
_LINES = "(SELECT o_orderkey, o_custkey, l_partkey, l_suppkey FROM orders JOIN lineitem ON o_orderkey = l_orderkey)"

#: name -> (select of src, dst[, w] with src < dst and no repeats, number of nodes)
GRAPHS = {
    "order_part": (f"SELECT DISTINCT l_orderkey AS src, {T['orders']} + l_partkey AS dst FROM lineitem", f"{T['orders']} + {T['part']}"),
    "order_supp": (f"SELECT DISTINCT l_orderkey AS src, {T['orders']} + l_suppkey AS dst FROM lineitem", f"{T['orders']} + {T['supplier']}"),
    "part_supp": (f"SELECT DISTINCT l_partkey AS src, {T['part']} + l_suppkey AS dst FROM lineitem", f"{T['part']} + {T['supplier']}"),
    "copurchase": ("SELECT DISTINCT a.l_partkey AS src, b.l_partkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_partkey < b.l_partkey", T["part"]),
    "coship": ("SELECT DISTINCT a.l_suppkey AS src, b.l_suppkey AS dst FROM lineitem a JOIN lineitem b ON a.l_orderkey = b.l_orderkey AND a.l_suppkey < b.l_suppkey", T["supplier"]),
    "cust_part": (f"SELECT DISTINCT o_custkey AS src, {T['customer']} + l_partkey AS dst FROM {_LINES}", f"{T['customer']} + {T['part']}"),
    "cust_order": (f"SELECT DISTINCT o_custkey AS src, {T['customer']} + o_orderkey AS dst FROM orders", f"{T['customer']} + {T['orders']}"),
    "event_chain": ("SELECT DISTINCT least(a, b) AS src, greatest(a, b) AS dst FROM (SELECT event_id AS a, lead(event_id) OVER (PARTITION BY user_id ORDER BY ts, event_id) AS b FROM events) WHERE b IS NOT NULL", T["events"]),
    "event_time": ("SELECT a.event_id AS src, b.event_id AS dst FROM events a JOIN (SELECT *, unnest(range(1, 31)) AS g FROM events) b ON b.event_id - b.g = a.event_id WHERE abs(epoch_us(b.ts) - epoch_us(a.ts)) <= 600000000", T["events"]),
    "doc_lines": (
        "WITH l AS (SELECT DISTINCT doc_id, trim(x) AS l FROM (SELECT doc_id, unnest(string_split(text, chr(10))) AS x FROM documents) WHERE length(trim(x)) >= 20),"
        " k AS (SELECT l FROM l GROUP BY l HAVING count(*) BETWEEN 2 AND 50)"
        " SELECT DISTINCT a.doc_id AS src, b.doc_id AS dst FROM l a JOIN k USING (l) JOIN l b USING (l) WHERE a.doc_id < b.doc_id",
        T["documents"],
    ),
    "emb_cos": ("SELECT a.vec_id AS src, b.vec_id AS dst FROM embeddings a JOIN embeddings b ON a.vec_id < b.vec_id WHERE list_cosine_similarity(a.embedding::DOUBLE[], b.embedding::DOUBLE[]) >= 0.25", T["embeddings"]),
    "page_anchor": (
        "WITH a AS (SELECT DISTINCT page_id, unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS p FROM pages)"
        f" SELECT page_id AS src, {T['pages']} + dense_rank() OVER (ORDER BY p) - 1 AS dst FROM a",
        f"{T['pages']} + (SELECT count(DISTINCT p) FROM (SELECT unnest(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1)) AS p FROM pages))",
    ),
    "conv": (
        "WITH t AS (SELECT conv_id, row_number() OVER (ORDER BY conv_id, turn) - 1 AS v FROM conversations)"
        " SELECT a.v AS src, b.v AS dst FROM t a JOIN t b ON a.conv_id = b.conv_id AND a.v < b.v",
        T["conversations"],
    ),
    "hierarchy": (
        f"SELECT n_regionkey::BIGINT AS src, (n_nationkey + 5)::BIGINT AS dst FROM nation UNION ALL SELECT c_nationkey + 5, c_custkey + 30 FROM customer UNION ALL SELECT s_nationkey + 5, s_suppkey + 30 + {T['customer']} FROM supplier",
        f"30 + {T['customer']} + {T['supplier']}",
    ),
    "cust_supp_weighted": (f"SELECT o_custkey AS src, {T['customer']} + l_suppkey AS dst, count(DISTINCT o_orderkey)::DOUBLE AS w FROM {_LINES} GROUP BY ALL", f"{T['customer']} + {T['supplier']}"),
    "grid": ("SELECT i AS src, i + 1 AS dst FROM range(400) t(i) WHERE i % 20 < 19 UNION ALL SELECT i, i + 20 FROM range(380) t(i)", "400"),
}


def edges_sql(name: str) -> str:
    sql, _ = GRAPHS[name]
    return f"SELECT src::BIGINT AS src, dst::BIGINT AS dst, {'w' if name == 'cust_supp_weighted' else '1.0::DOUBLE AS w'} FROM ({sql})"


def head(name: str) -> str:
    """The common tables `e` (edges) and `h` (n, m)."""
    return f"e AS MATERIALIZED ({edges_sql(name)}), h AS MATERIALIZED (SELECT ({GRAPHS[name][1]})::BIGINT AS n, (SELECT sum(w) FROM e)::DOUBLE AS m)"


def greedy(name: str, k: int, kappa: float = 1, gamma: float = 1.5, linear: bool = False, capacity: str = "hard") -> str:
    """Common tables ending in `a` (id, block): one recursion step per node over (labels, sizes, previous block)."""
    gain = "coalesce(list_sum(list_transform(range(1, len(st.nb) + 1), lambda j: CASE WHEN st.labels[st.nb[j] + 1] = x - 1 THEN st.ww[j] ELSE 0 END)), 0)"
    if linear:
        score = f"{gain} * (1 - st.sizes[x] / (st.n / {k}.0::DOUBLE))"
    elif gamma == 2:
        score = f"{gain} - st.m * {k} / (st.n * st.n) * 2 * st.sizes[x]"
    else:
        score = f"{gain} - st.m * sqrt({k}::DOUBLE) / (st.n * sqrt(st.n::DOUBLE)) * 1.5 * sqrt(st.sizes[x])"
    full = "st.sizes[x] >= st.lim" if capacity == "hard" else "false"
    stick = f"list_transform(range(1, {k + 1}), lambda x: CASE WHEN x - 1 = prev AND raw[x] > 0 THEN raw[x] * {kappa} WHEN x - 1 = prev AND raw[x] < 0 THEN raw[x] / {kappa} ELSE raw[x] END)"
    best = "list_position(sc, list_max(sc)) - 1"
    if linear:
        best = f"list_position(list_transform(range(1, {k + 1}), lambda x: CASE WHEN sc[x] = list_max(sc) THEN sizes[x] ELSE 1e300 END), list_min(list_transform(range(1, {k + 1}), lambda x: CASE WHEN sc[x] = list_max(sc) THEN sizes[x] ELSE 1e300 END))) - 1"
    raw = f"list_transform(range(1, {k + 1}), lambda x: CASE WHEN {full} THEN -1e300 ELSE {score} END)"
    masked = f"list_transform(range(1, {k + 1}), lambda x: CASE WHEN raw[x] = -1e300 THEN -1e300 ELSE stuck[x] END)"
    return f"""{head(name)}, back AS MATERIALIZED (SELECT dst, list(src) AS nb, list(w) AS ww FROM e GROUP BY dst),
c AS MATERIALIZED (SELECT n, m, ceil(103 * n / (100.0 * {k}))::BIGINT AS lim FROM h),
step(id, labels, sizes, prev) AS (
  SELECT -1::BIGINT, []::INTEGER[], list_transform(range({k}), lambda x: 0.0::DOUBLE), -1::INTEGER
  UNION ALL
  SELECT id + 1, list_append(labels, b), list_transform(sizes, lambda s, i: s + CASE WHEN i - 1 = b THEN 1 ELSE 0 END), b FROM (
    SELECT id, labels, sizes, ({best})::INTEGER AS b FROM (
      SELECT id, labels, sizes, {masked} AS sc FROM (
        SELECT id, labels, sizes, raw, {stick} AS stuck FROM (
          SELECT id, labels, sizes, prev, {raw} AS raw FROM (
            SELECT s.id, s.labels, s.sizes, s.prev, coalesce(b.nb, []) AS nb, coalesce(b.ww, []) AS ww, c.n, c.m, c.lim FROM step s CROSS JOIN c LEFT JOIN back b ON b.dst = s.id + 1 WHERE s.id + 1 < c.n
          ) st
        )
      )
    )
  )
), last AS (SELECT labels FROM step WHERE id = (SELECT n - 1 FROM c)),
a AS MATERIALIZED (SELECT (unnest(range(len(labels))))::BIGINT AS id, unnest(labels) AS block FROM last)"""


def mulshift(k: int) -> str:
    """Common table `a` by the multiply-shift hash, after `h`."""
    return f"a AS MATERIALIZED (SELECT i::BIGINT AS id, (((i::HUGEINT * 2654435761) % 4294967296) * {k} // 4294967296)::INTEGER AS block FROM h, range(h.n) t(i))"


RUNS = """q AS (SELECT *, sum(f) OVER (PARTITION BY batch ORDER BY pos) - 1 AS run_no FROM (SELECT *, CASE WHEN lag(sym) OVER (PARTITION BY batch ORDER BY pos) IS NOT DISTINCT FROM sym AND row_number() OVER (PARTITION BY batch ORDER BY pos) > 1 THEN 0 ELSE 1 END AS f FROM s)),
r AS MATERIALIZED (SELECT batch, run_no::BIGINT AS run_no, min(pos)::BIGINT AS start, count(*)::BIGINT AS len, any_value(sym) AS head FROM q GROUP BY batch, run_no)"""

SEQUENCES = {
    "events": "SELECT 0::BIGINT AS batch, event_id AS pos, event_type AS sym FROM events",
    "returnflag": "SELECT 0::BIGINT AS batch, row_number() OVER (ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_quantity) - 1 AS pos, l_returnflag AS sym FROM lineitem",
    "nation": "SELECT 0::BIGINT AS batch, c_custkey AS pos, c_nationkey AS sym FROM customer",
}

_HIER_ORDER = (
    "SELECT id AS i, row_number() OVER (ORDER BY region, depth, id) - 1 AS v FROM (SELECT r_regionkey::BIGINT AS id, r_regionkey AS region, 0 AS depth FROM region"
    " UNION ALL SELECT n_nationkey + 5, n_regionkey, 1 FROM nation"
    " UNION ALL SELECT c_custkey + 30, n_regionkey, 2 FROM customer JOIN nation ON c_nationkey = n_nationkey"
    f" UNION ALL SELECT s_suppkey + 30 + {T['customer']}, n_regionkey, 2 FROM supplier JOIN nation ON s_nationkey = n_nationkey)"
)


def _renumbered(name: str, numbers: str) -> tuple[str, str]:
    sql, n = GRAPHS[name]
    return f"WITH g AS ({sql}), d AS ({numbers.format(n=n)}) SELECT least(a.v, b.v) AS src, greatest(a.v, b.v) AS dst FROM g JOIN d a ON src = a.i JOIN d b ON dst = b.i", n


#: stream orders: breadth-first levels of the hierarchy, by falling degree, and by a hash of the id
GRAPHS["hierarchy_bfs"] = _renumbered("hierarchy", _HIER_ORDER)
GRAPHS["conv_degree"] = _renumbered("conv", "SELECT i, row_number() OVER (ORDER BY coalesce(deg, 0) DESC, i) - 1 AS v FROM (SELECT {n} AS n) h, range(h.n) t(i) LEFT JOIN (SELECT v, count(*) AS deg FROM (SELECT src AS v FROM g UNION ALL SELECT dst FROM g) GROUP BY v) ON v = i")
GRAPHS["conv_random"] = _renumbered("conv", f"SELECT i, row_number() OVER (ORDER BY {hashed_sql('i', 1)}, i) - 1 AS v FROM (SELECT {{n}} AS n) h, range(h.n) t(i)")


def sharded(name: str, k: int, shards: int, rounds: int = 2) -> str:
    """Common tables ending in `a` (id, block): every recursion step places one node of each shard; from the second round on
    nodes also count the blocks that earlier shards' nodes had in the round before."""
    size = f"list_transform(range({k}), lambda x: 0.0::DOUBLE)"
    gain = "coalesce(list_sum(list_transform(range(1, len(st.nb) + 1), lambda j: CASE WHEN st.labels[st.nb[j] + 1] = x - 1 THEN st.ww[j] ELSE 0 END)), 0)"
    far_gain = "coalesce(list_sum(list_transform(range(1, len(st.fb) + 1), lambda j: CASE WHEN st.fb[j] = x - 1 THEN st.fw[j] ELSE 0 END)), 0)"
    score = f"{gain} + {far_gain} - st.m * sqrt({k}::DOUBLE) / (st.n * sqrt(st.n::DOUBLE)) * 1.5 * sqrt(st.sizes[x] * st.p)"
    raw = f"list_transform(range(1, {k + 1}), lambda x: CASE WHEN st.sizes[x] >= st.cap THEN -1e300 ELSE {score} END)"
    out = f"""{head(name)}, c0 AS (SELECT n, m, ceil(103 * n / (100.0 * {k}))::BIGINT AS lim FROM h),
c AS MATERIALIZED (SELECT n, m, p, (n + p - 1) // p AS per, CASE WHEN p = 1 THEN lim ELSE lim // p END AS cap
  FROM (SELECT *, (SELECT max(q) FROM range(1, {shards + 1}) t(q) WHERE q = 1 OR lim // q >= ((n + q - 1) // q + {k - 1}) // {k}) AS p FROM c0)),
back AS MATERIALIZED (SELECT dst, list(src % per) AS nb, list(w) AS ww FROM e, c WHERE src // per = dst // per GROUP BY dst)"""
    for r in range(1, rounds + 1):
        told = f"SELECT dst, list(block) AS fb, list(w) AS fw FROM e JOIN a{r - 1} ON src = id, c WHERE src // per < dst // per GROUP BY dst" if r > 1 else "SELECT 0::BIGINT AS dst, []::INTEGER[] AS fb, []::DOUBLE[] AS fw WHERE false"
        out += f""", far{r} AS MATERIALIZED ({told}),
step{r}(shard, i, labels, sizes) AS (
  SELECT s, -1::BIGINT, []::INTEGER[], {size} FROM c, range(c.p) t(s)
  UNION ALL
  SELECT shard, i + 1, list_append(labels, b), list_transform(sizes, lambda x, j: x + CASE WHEN j - 1 = b THEN 1 ELSE 0 END) FROM (
    SELECT shard, i, labels, sizes, (list_position(raw, list_max(raw)) - 1)::INTEGER AS b FROM (
      SELECT shard, i, labels, sizes, {raw} AS raw FROM (
        SELECT s.shard, s.i, s.labels, s.sizes, coalesce(b.nb, []) AS nb, coalesce(b.ww, []) AS ww, coalesce(f.fb, []) AS fb, coalesce(f.fw, []) AS fw, c.n, c.m, c.p, c.cap
        FROM step{r} s CROSS JOIN c LEFT JOIN back b ON b.dst = s.shard * c.per + s.i + 1 LEFT JOIN far{r} f ON f.dst = s.shard * c.per + s.i + 1
        WHERE s.shard * c.per + s.i + 1 < least(c.n, (s.shard + 1) * c.per)
      ) st
    )
  )
),
a{r} AS MATERIALIZED (SELECT (shard * per + unnest(range(len(labels))))::BIGINT AS id, unnest(labels) AS block FROM step{r}, c WHERE i = least(n, (shard + 1) * per) - shard * per - 1)"""
    return f"{out}, a AS (SELECT * FROM a{rounds})"


def hyperbolic(n: int, degree: float, gamma: float = 2.9, seed: int = 42) -> str:
    """All pairs of the random hyperbolic graph's points, compared by their distance."""
    alpha = (gamma - 1) / 2
    xi = alpha / (alpha - 0.5)
    big = 2 * math.log(2 * n * xi * xi / (math.pi * degree))
    u, v = (f"({hashed_sql(x, seed)} + 0.5) / 2147483647.0::DOUBLE" for x in ("2 * i", "2 * i + 1"))
    return f"""WITH p AS (SELECT i, {v} * {2 * math.pi!r}::DOUBLE AS phi, 1 + {u} * {math.cosh(alpha * big) - 1!r}::DOUBLE AS y FROM range({n}) t(i)),
q AS MATERIALIZED (SELECT row_number() OVER (ORDER BY phi, i) - 1 AS id, phi, ln(y + sqrt(y * y - 1)) / {alpha!r}::DOUBLE AS r FROM p)
SELECT a.id::BIGINT AS src, b.id::BIGINT AS dst, 1.0::DOUBLE AS w FROM q a JOIN q b ON a.id < b.id WHERE cosh(a.r) * cosh(b.r) - sinh(a.r) * sinh(b.r) * cos(a.phi - b.phi) <= {math.cosh(big)!r}::DOUBLE"""


def delaunay(n: int, seed: int = 42) -> str:
    """Pairs of points whose largest opposite angles on both sides add up to at most half a turn."""
    x, y = (f"{hashed_sql(e, seed)} / 2147483647.0::DOUBLE" for e in ("2 * i", "2 * i + 1"))
    return f"""WITH p AS (SELECT i, {x} AS x, {y} AS y FROM range({n}) t(i)), q AS MATERIALIZED (SELECT row_number() OVER (ORDER BY x, y, i) - 1 AS id, x, y FROM p),
s AS (SELECT a.id AS src, b.id AS dst, (b.x - a.x) * (c.y - a.y) - (b.y - a.y) * (c.x - a.x) AS side, (a.x - c.x) * (b.x - c.x) + (a.y - c.y) * (b.y - c.y) AS dot FROM q a JOIN q b ON a.id < b.id JOIN q c ON c.id <> a.id AND c.id <> b.id)
SELECT src::BIGINT AS src, dst::BIGINT AS dst, 1.0::DOUBLE AS w FROM s GROUP BY src, dst
HAVING coalesce(min(dot / side) FILTER (side > 0), 1e300) + coalesce(min(dot / -side) FILTER (side < 0), 1e300) >= 0"""
