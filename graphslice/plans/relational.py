"""Relational queries around placements: one per operator family, each with its SQL."""

from __future__ import annotations

from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..operators import graph as gr, measure as me, runs as rl
from ..operators.durable import written
from ..sources import tables as ta
from . import execute as ex, oracles as o

QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _add(name, sql=None):
    def put(f):
        QUERIES[name] = f
        if sql:
            ORACLES[name] = sql
        return f

    return put


def labelled(s, d, name="order_part", k=4, method="mulshift"):
    edges, n = ta.BUILDERS[name](s, d)
    return edges, ex.hash_blocks(s.range(n), k, method)


_H = f"WITH {o.head('order_part')}, {o.mulshift(4)}"
_T = f"{_H}, t AS (SELECT src, dst, x.block AS p, y.block AS q FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id)"


@_add("q_filter_edges", f"SELECT DISTINCT l_orderkey AS src, {o.T['orders']} + l_partkey AS dst FROM lineitem WHERE l_quantity BETWEEN 10 AND 40 AND l_returnflag IN ('A', 'R')")
def filter_edges(s, d):
    x = ta.read(s, d, "lineitem").filter("l_quantity between 10 and 40 and l_returnflag in ('A', 'R')")
    return x.select(F.col("l_orderkey").alias("src"), (F.col("l_partkey") + ta.size(s, d, "orders")).alias("dst")).distinct()


for _hint in ("broadcast", "merge", "shuffle_hash"):
    _add(f"q_edge_blocks_{_hint}", f"WITH {o.head('part_supp')}, {o.mulshift(4)} SELECT src, dst, x.block AS src_block, y.block AS dst_block FROM e JOIN a x ON src = x.id JOIN a y ON dst = y.id")(lambda s, d, h=_hint: me.edge_blocks(*labelled(s, d, "part_supp"), h).select("src", "dst", "src_block", "dst_block"))


@_add("q_size_dominates", f"{_H}, z AS (SELECT block, count(*) AS size FROM a GROUP BY block) SELECT x.block AS a, y.block AS b FROM z x JOIN z y ON x.size > y.size")
def size_dominates(s, d):
    z = me.block_sizes(labelled(s, d)[1], 4)  # k rows
    return z.select(F.col("block").alias("a"), "size").join(F.broadcast(z.select(F.col("block").alias("b"), F.col("size").alias("other"))), F.col("size") > F.col("other")).select("a", "b")


_POS = f"SELECT pos, sym AS head FROM ({o.SEQUENCES['events']})"
for _name, _f in (("range", rl.lookup_few), ("asof", rl.lookup)):
    _add(f"q_run_of_position_{_name}", _POS)(lambda s, d, f=_f: f(written(rl.rle_encode(ta.read(s, d, "events"), "event_id", "event_type"), "runs"), ta.read(s, d, "events").select(F.col("event_id").alias("pos")), "pos", "head", 500))


@_add("q_isolated_orders", "SELECT o_orderkey FROM orders WHERE NOT EXISTS (SELECT 1 FROM lineitem WHERE l_orderkey = o_orderkey)")
def isolated_orders(s, d):
    return ta.read(s, d, "orders").select("o_orderkey").join(ta.read(s, d, "lineitem").select(F.col("l_orderkey").alias("o_orderkey")), "o_orderkey", "left_anti")


@_add("q_inner_edges", f"{_T} SELECT src, dst FROM t WHERE p = 0 AND q = 0")
def inner_edges(s, d):
    e, a = labelled(s, d)
    return gr.subgraph(e, a.filter("block = 0").select("id")).select("src", "dst")


@_add("q_back_neighbours", f"WITH {o.head('hierarchy')} SELECT i::BIGINT AS id, coalesce(src, -1) AS nbr FROM h, range(h.n) t(i) LEFT JOIN e ON dst = i")
def back_neighbours(s, d):
    e, n = ta.BUILDERS["hierarchy"](s, d)
    return s.range(n).join(gr.forward_adjacency(e).select("id", "nbr"), "id", "left").select("id", F.coalesce("nbr", F.lit(-1)).alias("nbr"))


@_add("q_degree_compare", f"WITH e AS ({o.edges_sql('event_time')}), x AS (SELECT src AS id, count(*) AS later FROM e GROUP BY src), y AS (SELECT dst AS id, count(*) AS earlier FROM e GROUP BY dst) SELECT coalesce(x.id, y.id) AS id, coalesce(later, 0) AS later, coalesce(earlier, 0) AS earlier FROM x FULL JOIN y ON x.id = y.id")
def degree_compare(s, d):
    e, _ = ta.BUILDERS["event_time"](s, d)
    return e.groupBy(F.col("src").alias("id")).agg(F.count("*").alias("later")).join(e.groupBy(F.col("dst").alias("id")).agg(F.count("*").alias("earlier")), "id", "full").select("id", F.coalesce("later", F.lit(0)).alias("later"), F.coalesce("earlier", F.lit(0)).alias("earlier"))


@_add("q_copurchase", f"SELECT src, dst FROM ({o.GRAPHS['copurchase'][0]})")
def copurchase(s, d):
    return ta.BUILDERS["copurchase"](s, d)[0].select("src", "dst")


@_add("q_block_grid", f"WITH {o.head('conv')} SELECT i::BIGINT AS id, b::INTEGER AS block, round(-(m * sqrt(4::DOUBLE) / (n * sqrt(n::DOUBLE)) * 1.5) * sqrt((b + 1)::DOUBLE), 9) AS score FROM h, range(h.n) t(i), range(4) u(b)")
def block_grid(s, d):
    """Scores of gainless blocks of size 1, 2, 3, 4 for every node: k rows per node by an array, no join."""
    from ..functions.score import PowerPenalty

    e, n = ta.BUILDERS["conv"](s, d)
    m = e.count()
    grid = s.range(n).withColumn("block", F.explode(F.sequence(F.lit(0), F.lit(3))))
    return grid.select("id", "block", F.round(PowerPenalty().column(F.lit(0.0), (F.col("block") + 1).cast("double"), n, m, 4), 9).alias("score"))


@_add("q_degree", f"WITH e AS ({o.edges_sql('cust_part')}) SELECT v AS id, count(*) AS degree FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v")
def degree(s, d):
    return gr.degrees(ta.BUILDERS["cust_part"](s, d)[0])


_add("q_block_sizes", f"{_H} SELECT block, count(*)::DOUBLE AS size FROM a GROUP BY block")(lambda s, d: me.block_sizes(labelled(s, d)[1], 4))
_add("q_block_boundary", f"{_T} SELECT block, count(DISTINCT id) AS nodes FROM (SELECT p AS block, src AS id FROM t WHERE p <> q UNION ALL SELECT q, dst FROM t WHERE p <> q) GROUP BY block")(lambda s, d: me.boundary(*labelled(s, d)))


@_add("q_boundary_approx")
def boundary_approx(s, d):
    x = me.edge_blocks(*labelled(s, d)).filter("src_block <> dst_block")
    return x.groupBy("src_block").agg(F.approx_count_distinct("src").alias("nodes"))


@_add("q_cut_cube", f"{_T} SELECT coalesce(p, -1) AS src_block, coalesce(q, -1) AS dst_block, count(*) AS edges FROM t WHERE p <> q GROUP BY CUBE (p, q)")
def cut_cube(s, d):
    return me.edge_blocks(*labelled(s, d)).filter("src_block <> dst_block").cube("src_block", "dst_block").agg(F.count("*").alias("edges")).select(F.coalesce("src_block", F.lit(-1)).alias("src_block"), F.coalesce("dst_block", F.lit(-1)).alias("dst_block"), "edges")


@_add("q_rollup", "SELECT coalesce(r_name, 'all') AS region, coalesce(n_name, 'all') AS nation, coalesce((c_custkey % 4)::INTEGER, -1) AS block, count(*) AS customers FROM region JOIN nation ON r_regionkey = n_regionkey JOIN customer ON n_nationkey = c_nationkey GROUP BY ROLLUP (r_name, n_name, (c_custkey % 4)::INTEGER)")
def rollup(s, d):
    c = ta.read(s, d, "customer").select("c_nationkey", (F.col("c_custkey") % 4).cast("int").alias("block"))
    x = ta.read(s, d, "region").join(ta.read(s, d, "nation"), F.col("r_regionkey") == F.col("n_regionkey")).join(c, F.col("n_nationkey") == F.col("c_nationkey"))
    return x.select(F.col("r_name").alias("region"), F.col("n_name").alias("nation"), "block").rollup("region", "nation", "block").agg(F.count("*").alias("customers")).select(F.coalesce("region", F.lit("all")).alias("region"), F.coalesce("nation", F.lit("all")).alias("nation"), F.coalesce("block", F.lit(-1)).alias("block"), "customers")


@_add("q_quotient_matrix", f"{_T} SELECT p AS src_block, count(*) FILTER (q = 0) AS b0, count(*) FILTER (q = 1) AS b1, count(*) FILTER (q = 2) AS b2, count(*) FILTER (q = 3) AS b3 FROM t GROUP BY p")
def quotient_matrix(s, d):
    x = me.edge_blocks(*labelled(s, d)).groupBy("src_block").pivot("dst_block", [0, 1, 2, 3]).agg(F.count(F.lit(1)))
    return x.select("src_block", *[F.coalesce(F.col(str(b)), F.lit(0)).alias(f"b{b}") for b in range(4)])


@_add("q_top_degree_per_block", f"{_H}, g AS (SELECT v, count(*) AS degree FROM (SELECT src AS v FROM e UNION ALL SELECT dst FROM e) GROUP BY v) SELECT * FROM (SELECT block, id, degree, row_number() OVER w AS place, rank() OVER w2 AS rank, dense_rank() OVER w2 AS dense FROM a JOIN g ON v = id WINDOW w AS (PARTITION BY block ORDER BY degree DESC, id), w2 AS (PARTITION BY block ORDER BY degree DESC)) WHERE place <= 5")
def top_degree(s, d):
    e, a = labelled(s, d)
    x = a.join(gr.degrees(e), "id")
    w, w2 = Window.partitionBy("block").orderBy(F.desc("degree"), "id"), Window.partitionBy("block").orderBy(F.desc("degree"))
    return x.select("block", "id", "degree", F.row_number().over(w).cast("long").alias("place"), F.rank().over(w2).cast("long").alias("rank"), F.dense_rank().over(w2).cast("long").alias("dense")).filter("place <= 5")


@_add("q_run_borders", "SELECT user_id, event_id, event_type, lag(event_type) OVER w AS before, lead(event_type) OVER w AS after, first_value(event_type) OVER w AS first FROM events WINDOW w AS (PARTITION BY user_id ORDER BY event_id)")
def run_borders(s, d):
    w = Window.partitionBy("user_id").orderBy("event_id")
    return ta.read(s, d, "events").select("user_id", "event_id", "event_type", F.lag("event_type").over(w).alias("before"), F.lead("event_type").over(w).alias("after"), F.first("event_type").over(w).alias("first"))


@_add("q_running_size", f"{_H} SELECT id, block, count(*) OVER (PARTITION BY block ORDER BY id ROWS UNBOUNDED PRECEDING) AS size FROM a")
def running_size(s, d):
    return labelled(s, d)[1].withColumn("size", F.count("*").over(Window.partitionBy("block").orderBy("id").rowsBetween(Window.unboundedPreceding, 0)))


@_add("q_recent_events", "SELECT event_id, count(*) OVER (PARTITION BY user_id ORDER BY epoch_us(ts) RANGE BETWEEN 3600000000 PRECEDING AND CURRENT ROW) AS recent FROM events")
def recent_events(s, d):
    w = Window.partitionBy("user_id").orderBy("us").rangeBetween(-3_600_000_000, 0)
    return ta.read(s, d, "events").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).select("event_id", F.count("*").over(w).alias("recent"))


@_add("q_heaviest_cut_pairs", f"{_T} SELECT least(p, q) AS a, greatest(p, q) AS b, count(*) AS edges FROM t WHERE p <> q GROUP BY ALL ORDER BY edges DESC, a, b LIMIT 3")
def heaviest_pairs(s, d):
    return me.quotient(*labelled(s, d)).filter("a <> b").orderBy(F.desc("edges"), "a", "b").limit(3)


@_add("q_longest_runs", f"WITH s AS ({o.SEQUENCES['events']}), {o.RUNS} SELECT start, len, head FROM r ORDER BY len DESC, start LIMIT 10")
def longest_runs(s, d):
    return rl.rle_encode(ta.read(s, d, "events"), "event_id", "event_type").select("start", "len", "head").orderBy(F.desc("len"), "start").limit(10)


@_add("q_moved_nodes", f"{_H} SELECT id, block FROM a EXCEPT ALL SELECT id, (id % 4)::INTEGER FROM a")
def moved_nodes(s, d):
    _, a = labelled(s, d)
    return a.exceptAll(ex.hash_blocks(a.select("id"), 4, "mod"))


@_add("q_common_cut", f"{_T} SELECT src, dst FROM t WHERE p <> q INTERSECT SELECT src, dst FROM e WHERE src % 4 <> dst % 4")
def common_cut(s, d):
    e, a = labelled(s, d)
    cut = lambda x: me.edge_blocks(e, x).filter("src_block <> dst_block").select("src", "dst")
    return cut(a).intersect(cut(ex.hash_blocks(a.select("id"), 4, "mod")))


@_add("q_anchors", "SELECT page_id, len(regexp_extract_all(html, 'href=\"(/[^\"]*)\"', 1))::BIGINT AS anchors, length(trim(url)) AS url_length FROM pages")
def anchors(s, d):
    return ta.read(s, d, "pages").select("page_id", F.size(F.regexp_extract_all("html", F.lit('href="(/[^"]*)"'), F.lit(1))).cast("long").alias("anchors"), F.length(F.trim("url")).cast("long").alias("url_length"))


@_add("q_events_by_hour", "SELECT strftime(date_trunc('hour', ts), '%Y-%m-%d %H:%M:%S') AS hour, count(*) AS n FROM events GROUP BY ALL")
def events_by_hour(s, d):
    return ta.read(s, d, "events").groupBy(F.date_format(F.date_trunc("hour", F.col("ts").cast("timestamp")), "yyyy-MM-dd HH:mm:ss").alias("hour")).agg(F.count("*").alias("n"))


@_add("q_math", f"{_H}, z AS (SELECT block, count(*) AS n FROM a GROUP BY block) SELECT block, round(sqrt(n::DOUBLE), 6) AS root, ceil(log2(n::DOUBLE))::BIGINT AS bits, bit_count(n)::BIGINT AS ones, sign(n - 4250)::BIGINT AS side, (n >> 3) AS eighth FROM z")
def math_functions(s, d):
    n = F.col("n")
    return labelled(s, d)[1].groupBy("block").agg(F.count("*").alias("n")).select("block", F.round(F.sqrt(n), 6).alias("root"), F.ceil(F.log2(n.cast("double"))).cast("long").alias("bits"), F.bit_count(n).cast("long").alias("ones"), F.signum(n - 4250).cast("long").alias("side"), F.shiftright(n, 3).alias("eighth"))


@_add("q_gain_maps", f"WITH {o.head('hierarchy')}, {o.mulshift(4)}, g AS (SELECT dst AS id, block, count(*) AS c FROM e JOIN a ON src = a.id GROUP BY ALL) SELECT id, string_agg(block || ':' || c, ',' ORDER BY block) AS gains FROM g GROUP BY id")
def gain_maps(s, d):
    e, a = labelled(s, d, "hierarchy")
    g = ex.forward_messages(a, e).groupBy(F.col("target").alias("id"), "block").agg(F.count("*").alias("c"))
    m = g.groupBy("id").agg(F.map_from_entries(F.sort_array(F.collect_list(F.struct("block", "c")))).alias("m"))
    return m.select("id", F.array_join(F.transform(F.map_entries("m"), lambda x: F.concat_ws(":", x["key"].cast("string"), x["value"].cast("string"))), ",").alias("gains"))


@_add("q_event_attributes", "SELECT event_id, json_extract_string(props, '$.k') AS k FROM events")
def event_attributes(s, d):
    return ta.read(s, d, "events").select("event_id", F.get_json_object("props", "$.k").alias("k"))


@_add("q_edge_sample", f"WITH e AS ({o.edges_sql('order_part')}) SELECT src, dst FROM e WHERE (src * 31 + dst * 17) % 10 = 0")
def edge_sample(s, d):
    """A repeatable sample: one edge in ten by its ends."""
    return ta.BUILDERS["order_part"](s, d)[0].filter("pmod(src * 31 + dst * 17, 10) = 0").select("src", "dst")


@_add("q_sql_surface", f"{_T} SELECT p AS block, count(*) AS cut FROM t WHERE p <> q GROUP BY p")
def sql_surface(s, d):
    e, a = labelled(s, d)
    e.createOrReplaceTempView("graph_edges")
    a.createOrReplaceTempView("graph_labels")
    return s.sql("SELECT x.block, count(*) AS cut FROM graph_edges JOIN graph_labels x ON src = x.id JOIN graph_labels y ON dst = y.id WHERE x.block <> y.block GROUP BY x.block")
