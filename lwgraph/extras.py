"""Queries of the decomposition, the oracles, degree expansion, Python functions and streams."""

from __future__ import annotations

import time

from pyspark.sql import functions as F

from .functions import python_functions as pf
from .operators import blocks, connect, decompose, degree
from .operators.joins import salted_join
from .operators.oracles import BiconnectivityOracle, ConnectivityOracle
from .plans.graph import CostMeter, Graph
from .plans.scratch import materialize, new_scratch_path
from .sources import oracle
from .sources.edge_source import generated, grid_over
from .sources.views import graph_view, hash_threshold, load
from .streaming import streams
from .workloads import ALL_PAIRS, RANGE, SAME, all_pairs, grouped_components, grouped_sql, kept

QUERIES: dict = {}
ORACLES: dict[str, str] = {}
NONE = "select cast(0 as bigint) as violations"


def query(sql: str | None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return register


def mesh(spark, d):
    """The event mesh, written once for all that is built on it."""
    return kept(spark, ("mesh-graph", d), lambda: graph_view(spark, d, "event_mesh").fixed())


def mesh_decomposition(spark, d, mode="recursive", k=8):
    return kept(spark, ("mesh", d, mode, k), lambda: decompose.decompose(mesh(spark, d), k, 1, mode=mode))


@query(f"select event_id as vid from events where substr(md5(concat_ws(':', '1', cast(event_id as varchar))), 1, 8) < '{hash_threshold(1 / 8)}'")
def d1_sample_primaries(spark, d):
    return decompose.sample_primaries(graph_view(spark, d, "event_mesh"), 8, 1)


def _nearest_sql() -> str:
    return f"""with recursive p as materialized ({oracle.edge_sql('event_mesh')}), s as materialized (select distinct x as u, y as v from p where y is not null union select distinct y, x from p where y is not null),
dep(vid, d) using key (vid) as (
  select event_id, case when substr(md5(concat_ws(':', '1', cast(event_id as varchar))), 1, 8) < '{hash_threshold(1 / 8)}' then 0 else 1000000000 end from events
  union
  select s.v, min(dep.d) + 1 from dep join s on s.u = dep.vid join recurring.dep r on r.vid = s.v where dep.d + 1 < r.d group by s.v),
nxt as materialized (select y.vid, min(s.u) as up from dep y join s on s.v = y.vid join dep x on x.vid = s.u and x.d = y.d - 1 group by y.vid),
walk(vid, spot) as (select vid, vid from dep union all select walk.vid, nxt.up from walk join nxt on nxt.vid = walk.spot)
select w.vid, w.spot as primary, cast(q.d as integer) as hop from walk w join dep q on q.vid = w.vid join dep z on z.vid = w.spot where z.d = 0"""


@query(_nearest_sql().replace("as primary", 'as "primary"'))
def d3_primary_of(spark, d):
    """Nearest primary by the lexicographically least shortest path."""
    return mesh_decomposition(spark, d).hops.select("vid", "primary", "hop")


@query("select cast(0 as bigint) as lost, cast(0 as bigint) as oversized, cast(0 as bigint) as broken")
def d8_decomposition_check(spark, d):
    return decompose.check_decomposition(mesh_decomposition(spark, d)).select("lost", "oversized", "broken")


@query("select cast(0 as bigint) as lost, cast(0 as bigint) as oversized, cast(0 as bigint) as broken")
def d7_levelwise_check(spark, d):
    return decompose.check_decomposition(mesh_decomposition(spark, d, "levelwise")).select("lost", "oversized", "broken")


@query(NONE)
def d4q_implicit_lookup(spark, d):
    """Looking up every vertex by its own search gives the batch answer."""
    dec = mesh_decomposition(spark, d)
    asked = graph_view(spark, d, "event_mesh").vertices
    found = decompose.lookup_center(dec, asked)
    wrong = found.join(dec.lookup().select("vid", F.col("center").alias("want")), "vid", "left").filter(~F.col("center").eqNullSafe(F.col("want")))
    return wrong.agg(F.count(F.lit(1)).alias("violations"))


@query(f"select * from (with answers as ({oracle.components('event_mesh')}) select count(distinct comp) as components from answers)")
def d12_quotient_components(spark, d):
    """The quotient hangs together as the graph does: as many components, clusters for vertices."""
    dec = mesh_decomposition(spark, d)
    where = dec.lookup()
    q = decompose.quotient(dec.graph, where).select(F.col("ca").alias("a"), F.col("cb").alias("b"))
    return connect.components_star(Graph(where.select(F.col("center").alias("vid")).distinct(), q)).agg(F.countDistinct("comp").alias("components"))


@query(None)
def d12_quotient(spark, d):
    dec = mesh_decomposition(spark, d)
    return decompose.quotient(dec.graph, dec.lookup())


@query(None)
def d13_quotient_neighbors(spark, d):
    return decompose.quotient_neighbors(mesh_decomposition(spark, d))


@query(NONE)
def d13_implicit_neighbors(spark, d):
    """Neighbours of all clusters by outward searches and look-ups of the far ends are those of the batch."""
    dec = mesh_decomposition(spark, d)
    want = decompose.quotient_neighbors(dec)
    found = materialize(decompose.quotient_neighbors(dec, dec.lookup().select("center").distinct()), "neighbors")
    return found.exceptAll(want).unionByName(want.exceptAll(found)).agg(F.count(F.lit(1)).alias("violations"))


@query(None)
def d14_primary_only_sizes(spark, d):
    """Cluster sizes without secondary centers: no bound."""
    dec = mesh_decomposition(spark, d, "primary_only")
    return dec.lookup().groupBy("center").agg(F.count(F.lit(1)).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("clusters"))


@query("select cast(0 as bigint) as lost, cast(0 as bigint) as broken")
def d16_ball_clusters(spark, d):
    """Balls as clusters: every vertex has a center and every cluster hangs together; sizes are not bounded."""
    return decompose.check_decomposition(mesh_decomposition(spark, d, "balls", 2)).select("lost", "broken")


@query(None)
def d16_ball_sizes(spark, d):
    return mesh_decomposition(spark, d, "balls", 2).lookup().groupBy("center").agg(F.count(F.lit(1)).alias("n")).groupBy("n").agg(F.count(F.lit(1)).alias("clusters"))


@query("""with o as (select o_orderkey as x, lead(o_orderkey) over w as beside, lead(o_orderkey, 40) over w as below, row_number() over w as n from orders window w as (order by o_orderkey))
select x, beside as y from o where n % 40 <> 0 and beside is not null union all select x, below from o where below is not null""")
def s7_generated_grid(spark, d):
    """A grid made over the orders in the order of their keys, 40 to a line."""
    return grid_over(load(spark, d, "orders", "o_orderkey"), 40)


@query("select i as vid, cast(0 as bigint) as comp from range(0, 1600) t(i)")
def s7_grid_components(spark, d):
    """Low-write connectivity on a generated grid."""
    return connect.components_lowwrite(Graph.of(generated(spark, "grid", 40)).fixed(), beta=0.5)


@query("select s_nationkey, count(*) as lines, cast(sum(l_linenumber) as bigint) as numbers from lineitem join supplier on l_suppkey = s_suppkey group by s_nationkey")
def j10_salted_join(spark, d):
    lines = load(spark, d, "lineitem", "l_suppkey", "l_orderkey", "l_linenumber").withColumnRenamed("l_suppkey", "s_suppkey")
    joined = salted_join(lines, load(spark, d, "supplier", "s_suppkey", "s_nationkey"), "s_suppkey", ["l_orderkey", "l_linenumber"])
    return joined.groupBy("s_nationkey").agg(F.count(F.lit(1)).alias("lines"), F.sum("l_linenumber").cast("bigint").alias("numbers"))


@query(None)
def w3_k_sweep(spark, d):
    """Centers * k / n and largest cluster for each k: the first stays flat."""
    out, g = None, mesh(spark, d)
    n = g.vertices.count()
    for k in (4, 8, 16):
        dec = mesh_decomposition(spark, d, k=k)
        one = dec.lookup().groupBy("center").agg(F.count(F.lit(1)).alias("s")).agg(F.max("s").alias("largest"), F.count(F.lit(1)).alias("clusters")).select(F.lit(k).alias("k"), "largest", "clusters", (F.col("clusters") * k / n).alias("clusters_k_over_n"))
        out = one if out is None else out.unionByName(one)
    return out


def mesh_oracle(spark, d):
    return kept(spark, ("c4", d), lambda: ConnectivityOracle.build(mesh(spark, d), k=8, seed=1))


@query(f"select * from (with answers as ({oracle.components('event_mesh')}) select cast(count(distinct comp) as bigint) as components, count(*) as vertices from answers)")
def c4_oracle_components(spark, d):
    return mesh_oracle(spark, d).component().agg(F.countDistinct("comp").alias("components"), F.count(F.lit(1)).alias("vertices"))


@query(f"select * from (with answers as ({oracle.components('order_fragments')}), named as (select comp, count(*) as size from answers group by comp) select size, count(*) as components from named group by size)")
def c4_oracle_fragments(spark, d):
    """Component sizes of many small trees: implicit centers, primaries of last resort."""
    o = kept(spark, ("c4f", d), lambda: ConnectivityOracle.build(graph_view(spark, d, "order_fragments"), k=4, quotient_mode="explicit"))
    return o.component().groupBy("comp").agg(F.count(F.lit(1)).alias("size")).groupBy("size").agg(F.count(F.lit(1)).alias("components"))


def slice_oracle(spark, d):
    """The 2-bounded conversation paths and page-like fragments: a bounded-degree view with blocks."""
    return kept(spark, ("bicon", d), lambda: BiconnectivityOracle.build(graph_view(spark, d, "order_chain"), k=4, seed=1))


@query(oracle.bridges("order_chain"))
def o6_bridges(spark, d):
    return slice_oracle(spark, d).is_bridge().filter("is_bridge").select("a", "b")


@query(oracle.articulation("order_chain"))
def o7_articulation(spark, d):
    return slice_oracle(spark, d).is_articulation()


@query(f"select * from (with answers as ({oracle.blocks('order_chain')}) select count(distinct (block_a, block_b)) as blocks from answers)")
def o12_block_count(spark, d):
    return slice_oracle(spark, d).block_count()


@query(SAME)
def o10_same_block(spark, d):
    """Every order with its successor and with a key dealt over the whole range."""
    return slice_oracle(spark, d).same_block(all_pairs(spark, d), batch=True)


@query(f"select * from (with answers as materialized ({oracle.two_edge('order_chain')}) select qid, x.comp = y.comp as same_edge_block from ({ALL_PAIRS}) join answers x on x.vid = u join answers y on y.vid = v)")
def o11_same_edge_block(spark, d):
    return slice_oracle(spark, d).same_edge_block(all_pairs(spark, d), batch=True)


@query(NONE)
def o10_few_pairs(spark, d):
    """Pairs asked a few at a time, each opening its own clusters only, get the answers of the batch."""
    o = slice_oracle(spark, d)
    pairs = materialize(all_pairs(spark, d).orderBy(F.md5(F.col("qid").cast("string"))).limit(40), "few-pairs")
    want = o.same_blocks(pairs, batch=True).toDF("qid", "want", "want_edge")
    got = o.same_blocks(pairs)
    return want.join(got, "qid", "full").filter("not (want <=> same_block) or not (want_edge <=> same_edge_block)").agg(F.count(F.lit(1)).alias("violations"))


@query(oracle.components("geo_tree"))
def u1_expanded_components(spark, d):
    """Components through degree expansion of the hubs."""
    g, names = degree.expand(graph_view(spark, d, "geo_tree").fixed(), 8)
    return degree.project_components(connect.components_star(g.fixed()), materialize(names, "names"))


@query(oracle.bridges("part_supplier_slice"))
def u3_expanded_bridges(spark, d):
    g, names = degree.expand(graph_view(spark, d, "part_supplier_slice").fixed(), 4, explicit=True)
    return degree.project_edges(blocks.bridges(blocks.block_labelling(g, beta=0.5)), materialize(names, "names"))


PERC = "select e.a as x, e.b as y from (select distinct least(x, y) as a, greatest(x, y) as b from ({e}) where y is not null) e where substr(md5(concat_ws(':', '5', cast(e.a as varchar), cast(e.b as varchar))), 1, 8) < '{t}'"


@query(f"select * from (with answers as ({oracle.components('event_mesh', edges=PERC.format(e=oracle.edge_sql('event_mesh'), t=hash_threshold(0.5)), vertices='select event_id as vid from events')}) select comp, count(*) as size from answers group by comp)")
def w6_percolation(spark, d):
    """Component sizes of a hash-sampled mesh that is never stored."""
    return connect.component_sizes(connect.components_star(graph_view(spark, d, "percolation", p=0.5, seed=5)))


@query(None)
def w9_store_costs(spark, d):
    """Rows stored by each structure on the mesh."""
    g = graph_view(spark, d, "event_mesh")
    meter = CostMeter("connectivity oracle")
    ConnectivityOracle.build(g, k=8, seed=1, meter=meter)
    return meter.report(spark, (1, 16, 256))


# --- functions and streams ----------------------------------------------------------------------


_COS = "round(list_cosine_similarity(cast(x.embedding as double[]), cast(y.embedding as double[])), 4)"


@query(f"select x.vec_id as a, y.vec_id as b, {_COS} as by_function, {_COS} as by_expression from embeddings x join embeddings y on y.vec_id = x.vec_id + 1")
def q_udf_cosine(spark, d):
    """The Arrow function and the expression side by side."""
    e = load(spark, d, "embeddings", "vec_id", "embedding")
    x, y = e.select(F.col("vec_id").alias("a"), F.col("embedding").alias("va"), (F.col("vec_id") + 1).alias("b")), e.select(F.col("vec_id").alias("b"), F.col("embedding").alias("vb"))
    return x.join(y, "b").select("a", "b", F.round(pf.cosine("va", "vb"), 4).alias("by_function"), F.round(pf.cosine_expression("va", "vb"), 4).alias("by_expression"))


@query("select n_nationkey as vid, cast(ceil(count(*) / 8.0) as bigint) * 2 - 1 as nodes from customer join nation on c_nationkey = n_nationkey group by 1 having count(*) > 8")
def q_udtf_expand(spark, d):
    pf.register(spark)
    load(spark, d, "customer", "c_nationkey").groupBy(F.col("c_nationkey").alias("vid")).agg(F.count(F.lit(1)).alias("degree")).createOrReplaceTempView("v_degrees")
    return spark.sql("select d.vid, count(*) as nodes from v_degrees d, lateral lw_expand_vertex(cast(d.vid as bigint), d.degree, 8) t group by d.vid")


_USERS = "select user_id as key, ascii(event_type) * 1000 + ascii(substr(event_type, 2)) as x, 1000000 + cast(props->>'$.k' as integer) % 5 as y from events where value > 100"


@query(f"select key as user_id, count(distinct comp) as components from ({grouped_sql(_USERS)}) group by key")
def q_udaf_components(spark, d):
    """Components of every user's own graph of event types and what costly events name, by a grouped aggregate."""
    e = load(spark, d, "events", "user_id", "event_type", "props", "value").filter("value > 100")
    a = F.ascii("event_type") * 1000 + F.ascii(F.substring("event_type", 2, 10))
    rows = e.select("user_id", a.cast("bigint").alias("a"), (F.pmod(F.get_json_object("props", "$.k").cast("int"), F.lit(5)) + 1_000_000).cast("bigint").alias("b"))
    return rows.groupBy("user_id").agg(pf.component_count("a", "b").alias("components"))


def in_time_order(events, path: str, files: int = 4, most: int = 2_000_000) -> None:
    """Ranges of ts, a file of some ``most`` rows each, one after the other: a stream takes files by their times, and files of
    one job end in any order, by which a later range would let the watermark pass rows of an earlier one."""
    at = F.unix_micros(F.col("ts").cast("timestamp"))
    files = max(files, -(-events.count() // most))
    bounds = events.agg(F.percentile_approx(at, [i / files for i in range(1, files)], 10_000)).head()[0] or []
    number = sum((F.coalesce(at >= F.lit(b), F.lit(False)).cast("int") for b in sorted(set(bounds))), F.lit(0))
    for i in range(len(set(bounds)) + 1):
        events.filter(number == i).repartition(1).write.mode("append").parquet(path)
        time.sleep(1.2)  # files are taken in the order of their times


def _event_files(spark, d) -> str:
    def build():
        path = new_scratch_path(spark, "event-files")
        in_time_order(load(spark, d, "events"), path)
        return path

    return kept(spark, ("event-files", d), build)


@query("select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from events group by all")
def q_stream_window(spark, d):
    out = streams.run_to_table(streams.window_counts(streams.event_stream(spark, _event_files(spark, d))), "window", "complete")
    return out.select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("""with e as (select user_id, ts, case when ts < lag(ts) over (partition by user_id order by ts) + interval 12 hours then 0 else 1 end as fresh from events),
s as (select user_id, ts, sum(fresh) over (partition by user_id order by ts rows unbounded preceding) as number from e)
select user_id, epoch_us(min(ts)) as start_us, count(*) as n from s group by user_id, number having max(ts) + interval 12 hours <= (select date_trunc('milliseconds', max(ts)) from events) - interval 2 days""")
def q_stream_session(spark, d):
    """Sessions that the watermark has closed, in append mode."""
    out = streams.run_to_table(streams.sessions(streams.event_stream(spark, _event_files(spark, d))), "session", "append")
    return out.select("user_id", F.unix_micros("start").alias("start_us"), "n")


@query("select distinct user_id, event_type from events")
def q_stream_dedupe(spark, d):
    return streams.run_to_table(streams.distinct_edges(streams.event_stream(spark, _event_files(spark, d))), "dedupe", "append")


_DAYS = "select cast(epoch(date_trunc('day', ts)) as bigint) // 86400 as key, user_id as x, 1000000 + cast(props->>'$.k' as bigint) as y from events"


@query(grouped_sql(_DAYS))
def q_stream_state(spark, d):
    """Components of every day's graph of users and what their events name, kept as state of the day: the last change of each label."""
    edges = streams.window_edges(streams.event_stream(spark, _event_files(spark, d)))
    rows, _, _ = streams.run_to_batches(streams.incremental_components(edges), "state", mode="append")
    return rows.groupBy("key", "vid").agg(F.min("comp").alias("comp"))


@query(grouped_sql(_DAYS))
def q_stream_window_graphs(spark, d):
    """The same graphs, each batch's edges reduced to a forest in a foreachBatch sink, all days solved at once in the end."""
    def forest(batch):
        pairs = batch.select((F.col("a") + F.col("key") * RANGE).alias("x"), (F.col("b") + F.col("key") * RANGE).alias("y"))
        kept_ = connect.partition_forest(Graph.of(pairs))
        key = F.floor(F.col("a") / RANGE).cast("bigint")
        return kept_.select(key.alias("key"), (F.col("a") - key * RANGE).alias("a"), (F.col("b") - key * RANGE).alias("b"))

    rows, _, _ = streams.run_to_batches(streams.window_edges(streams.event_stream(spark, _event_files(spark, d))), "graphs", mode="append", change=forest)
    return grouped_components(rows.select("key", F.col("a").alias("x"), F.col("b").alias("y")))


def _late_files(spark, d) -> str:
    """Purchases, then clicks, then everything else, a file each: rows are held against the watermark of the batch before."""
    def build():
        path, e = new_scratch_path(spark, "late-files"), load(spark, d, "events")
        for wanted in ("event_type = 'purchase'", "event_type = 'click'", "event_type not in ('purchase', 'click')"):
            e.filter(wanted).coalesce(1).write.mode("append").parquet(path)
            time.sleep(1.2)  # files are taken in the order of their times
        return path

    return kept(spark, ("late-files", d), build)


_KEPT_ROWS = """select * from events where event_type in ('purchase', 'click') or date_trunc('day', ts) + interval 1 day > (select date_trunc('milliseconds', max(ts)) from events where event_type = 'purchase') - interval 10 days"""


@query(f"select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from ({_KEPT_ROWS}) group by all")
def q_stream_late(spark, d):
    """Rows of windows that the watermark has passed are left out; update mode, the last update of each window."""
    rows, _, _ = streams.run_to_batches(streams.window_counts(streams.event_stream(spark, _late_files(spark, d)), delay="10 days"), "late")
    return streams.latest(rows, ["start", "event_type"]).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query("select strftime(date_trunc('day', ts), '%Y-%m-%d') as day, event_type, count(*) as n from events group by all")
def q_stream_restart(spark, d):
    """A stream that stops after half of the files and starts again from its checkpoint counts every row once."""
    path, e = new_scratch_path(spark, "restart-files"), load(spark, d, "events")
    half = F.pmod(F.xxhash64("event_id"), F.lit(2)) == 0
    counts = lambda: streams.window_counts(streams.event_stream(spark, path), delay="60 days")
    e.filter(half).coalesce(2).write.parquet(path)
    _, _, place = streams.run_to_batches(counts(), "restart")
    e.filter(~half).coalesce(2).write.mode("append").parquet(path)
    rows, _, _ = streams.run_to_batches(counts(), "restart", place)
    return streams.latest(rows, ["start", "event_type"]).select(F.date_format("start", "yyyy-MM-dd").alias("day"), "event_type", "n")


@query(f"select * from (with answers as ({oracle.components('event_mesh')}) select x.vid as qid, x.comp = y.comp as connected from answers x join answers y on y.vid = x.vid + 1)")
def q_stream_static(spark, d):
    """Streamed pairs of neighbouring events answered by the stored oracle."""
    comp = materialize(mesh_oracle(spark, d).component(), "static-components")
    pairs = streams.event_stream(spark, _event_files(spark, d)).select(F.col("event_id").alias("qid"), F.col("event_id").alias("u"), (F.col("event_id") + 1).alias("v"))
    return streams.run_to_table(streams.with_oracle(pairs, comp), "static", "append")


@query("""select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase'
          and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour""")
def q_stream_interval(spark, d):
    return streams.run_to_table(streams.click_to_purchase(streams.event_stream(spark, _event_files(spark, d))), "interval", "append")
