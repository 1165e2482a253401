"""Relational operators around the methods, as queries on the given tables with plain SQL beside them."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from .plans.scratch import materialize, session_setting
from .sources.views import edge_sql, graph_view, load

CHAIN = f"(select least(x, y) as a, greatest(x, y) as b, cast(count(*) as integer) as mult from ({edge_sql('order_chain')}) where x is not null and y is not null and x <> y group by 1, 2)"
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def query(sql: str | None):
    def register(f):
        QUERIES[f.__name__] = f
        if sql is not None:
            ORACLES[f.__name__] = sql
        return f

    return register


def chain(spark: SparkSession, sf_dir: str) -> DataFrame:
    return graph_view(spark, sf_dir, "order_chain").edges


def ends(edges: DataFrame) -> DataFrame:
    return edges.select(F.explode(F.array("a", "b")).alias("vid"))


@query("select l_orderkey, l_partkey from lineitem where l_quantity >= 45")
def q_scan_prune(spark, d):
    return load(spark, d, "lineitem", "l_orderkey", "l_partkey", "l_quantity").filter(F.col("l_quantity") >= 45).select("l_orderkey", "l_partkey")


@query(f"select a, b, mult from {CHAIN}")
def q_edge_canon(spark, d):
    return chain(spark, d).select("a", "b", "mult")


@query("select l_partkey, l_suppkey, count(*) as mult from lineitem group by all order by mult desc, l_partkey, l_suppkey limit 50")
def q_edge_mult(spark, d):
    return load(spark, d, "lineitem", "l_partkey", "l_suppkey").groupBy("l_partkey", "l_suppkey").agg(F.count(F.lit(1)).alias("mult")).orderBy(F.desc("mult"), "l_partkey", "l_suppkey").limit(50)


DEGREES = f"(select vid, count(*) as degree from (select a as vid from {CHAIN} union all select b from {CHAIN}) group by vid)"


@query(f"select vid, degree from {DEGREES}")
def q_degree(spark, d):
    return ends(chain(spark, d)).groupBy("vid").agg(F.count(F.lit(1)).alias("degree"))


@query(f"select degree, count(*) as vertices from {DEGREES} group by degree")
def q_degree_hist(spark, d):
    return q_degree(spark, d).groupBy("degree").agg(F.count(F.lit(1)).alias("vertices"))


@query(f"select cast(quantile_disc(degree, 0.5) as bigint) as p50, cast(quantile_disc(degree, 0.9) as bigint) as p90, cast(max(degree) as bigint) as top from {DEGREES}")
def q_degree_quantiles(spark, d):
    ranks = q_degree(spark, d).groupBy("degree").agg(F.count(F.lit(1)).alias("n"))
    run = ranks.withColumn("upto", F.sum("n").over(Window.orderBy("degree"))).withColumn("all", F.sum("n").over(Window.partitionBy()))  # one row a degree
    return run.agg(F.min(F.when(F.col("upto") >= F.col("all") * 0.5, F.col("degree"))).alias("p50"), F.min(F.when(F.col("upto") >= F.col("all") * 0.9, F.col("degree"))).alias("p90"), F.max("degree").alias("top"))


@query(f"select o_orderkey as vid from orders where o_orderkey not in (select vid from {DEGREES})")
def q_isolated(spark, d):
    return load(spark, d, "orders", "o_orderkey").withColumnRenamed("o_orderkey", "vid").join(ends(chain(spark, d)), "vid", "left_anti")


@query(f"select distinct o_custkey from orders where o_orderkey in (select vid from {DEGREES} where degree = 1)")
def q_touched(spark, d):
    leaves = q_degree(spark, d).filter("degree = 1").select(F.col("vid").alias("o_orderkey"))
    return load(spark, d, "orders", "o_orderkey", "o_custkey").join(leaves, "o_orderkey", "left_semi").select("o_custkey").distinct()


@query(f"select o_orderkey, coalesce(degree, 0) as degree from orders left join {DEGREES} on vid = o_orderkey")
def q_label_all(spark, d):
    deg = q_degree(spark, d).withColumnRenamed("vid", "o_orderkey")
    return load(spark, d, "orders", "o_orderkey").join(deg, "o_orderkey", "left").select("o_orderkey", F.coalesce("degree", F.lit(0)).alias("degree"))


@query("""select coalesce(c.k, s.k) as k, c.n as customers, s.n as suppliers from (select c_nationkey as k, count(*) as n from customer group by 1) c
          full join (select s_nationkey as k, count(*) as n from supplier where s_acctbal > 0 group by 1) s on c.k = s.k where c.n is distinct from s.n""")
def q_label_diff(spark, d):
    c = load(spark, d, "customer", "c_nationkey").groupBy(F.col("c_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("customers"))
    s = load(spark, d, "supplier", "s_nationkey", "s_acctbal").filter("s_acctbal > 0").groupBy(F.col("s_nationkey").alias("k")).agg(F.count(F.lit(1)).alias("suppliers"))
    return c.join(s, "k", "full").filter(~F.col("customers").eqNullSafe(F.col("suppliers"))).select("k", "customers", "suppliers")


@query(f"""select e.a, e.b from {CHAIN} e join orders p on p.o_orderkey = e.a join orders q on q.o_orderkey = e.b
           where abs(date_diff('day', cast(p.o_orderdate as date), cast(q.o_orderdate as date))) <= 30""")
def q_time_edges(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_orderdate").withColumn("day", F.to_date("o_orderdate"))
    x, y = o.select(F.col("o_orderkey").alias("a"), F.col("day").alias("da")), o.select(F.col("o_orderkey").alias("b"), F.col("day").alias("db"))
    return chain(spark, d).join(x, "a").join(y, "b").filter(F.abs(F.datediff("da", "db")) <= 30).select("a", "b")


@query("""select c.event_id as click_id, p.event_id as purchase_id from events c join events p on c.user_id = p.user_id and c.event_type = 'click' and p.event_type = 'purchase'
          and p.ts >= c.ts and p.ts <= c.ts + interval 1 hour""")
def q_interval_join(spark, d):
    """Hour bins turn the range condition into an equality: a purchase looks into its own bin and the one before."""
    e = load(spark, d, "events", "event_id", "user_id", "event_type", "ts").withColumn("bin", F.date_trunc("hour", "ts"))
    c = e.filter("event_type = 'click'").select("user_id", "bin", F.col("event_id").alias("click_id"), F.col("ts").alias("t0"))
    p = e.filter("event_type = 'purchase'").select("user_id", F.col("event_id").alias("purchase_id"), F.col("ts").alias("t1"), F.explode(F.array("bin", F.col("bin") - F.expr("interval 1 hour"))).alias("bin"))
    return c.join(p, ["user_id", "bin"]).filter("t1 >= t0 and t1 <= t0 + interval 1 hour").select("click_id", "purchase_id")


@query("""select p.event_id as purchase_id, (select v.event_id from events v where v.user_id = p.user_id and v.event_type = 'view' and (v.ts < p.ts or v.ts = p.ts and v.event_id < p.event_id) order by v.ts desc, v.event_id desc limit 1) as view_id
          from events p where p.event_type = 'purchase'""")
def q_asof(spark, d):
    """Latest earlier view of every purchase: one window over the user's events, no join."""
    e = load(spark, d, "events", "event_id", "user_id", "event_type", "ts").filter("event_type in ('view', 'purchase')")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    seen = e.withColumn("view_id", F.last(F.when(F.col("event_type") == "view", F.col("event_id")), ignorenulls=True).over(w))
    return seen.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), "view_id")


@query("select p.event_id as a, q.event_id as b from events p join events q on p.user_id = q.user_id and p.event_id < q.event_id and abs(epoch_us(p.ts) - epoch_us(q.ts)) <= 3600000000")
def q_theta(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp"))).withColumn("bin", F.expr("us div 3600000000"))
    p = e.select("user_id", F.col("event_id").alias("a"), F.col("us").alias("ua"), F.explode(F.array(F.col("bin") - 1, F.col("bin"), F.col("bin") + 1)).alias("bin"))
    q = e.select("user_id", F.col("event_id").alias("b"), F.col("us").alias("ub"), "bin")
    return p.join(q, ["user_id", "bin"]).filter("a < b and abs(ua - ub) <= 3600000000").select("a", "b")


@query("select n_name, (select count(*) from customer where c_nationkey = n_nationkey) + (select count(*) from supplier where s_nationkey = n_nationkey) as below from nation")
def q_contain(spark, d):
    """Descendants of each nation: subtree ranges of the rooted tree, size less one."""
    from .operators.blocks import root_forest

    g = graph_view(spark, d, "geo_tree")
    f = root_forest(g, g.edges.select("a", "b"))
    n = load(spark, d, "nation", "n_nationkey", "n_name").select("n_name", (F.col("n_nationkey") + 2 * 10**12).alias("vid"))
    return f.join(n, "vid").select("n_name", (F.col("size") - 1).alias("below"))


@query("select c_mktsegment, o_orderpriority, count(*) as orders from customer join orders on o_custkey = c_custkey group by rollup (c_mktsegment, o_orderpriority)")
def q_rollup(spark, d):
    return load(spark, d, "orders", "o_custkey", "o_orderpriority").join(load(spark, d, "customer", "c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey")).rollup("c_mktsegment", "o_orderpriority").agg(F.count(F.lit(1)).alias("orders"))


@query("select l_returnflag, l_linestatus, count(*) as lines, cast(grouping(l_returnflag) * 2 + grouping(l_linestatus) as bigint) as gid from lineitem group by cube (l_returnflag, l_linestatus)")
def q_cube(spark, d):
    return load(spark, d, "lineitem", "l_returnflag", "l_linestatus").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("lines"), F.grouping_id().alias("gid"))


@query("select l_returnflag as flag, cast(year(l_shipdate) as integer) as year, count(*) as lines from lineitem group by grouping sets ((l_returnflag), (year(l_shipdate)))")
def q_gsets(spark, d):
    df = load(spark, d, "lineitem", "l_returnflag", "l_shipdate").select(F.col("l_returnflag").alias("flag"), F.year("l_shipdate").alias("year"))
    return df.groupingSets([["flag"], ["year"]], "flag", "year").agg(F.count(F.lit(1)).alias("lines"))


@query("select l_partkey, count(distinct l_suppkey) as suppliers from lineitem group by l_partkey")
def q_distinct(spark, d):
    return load(spark, d, "lineitem", "l_partkey", "l_suppkey").groupBy("l_partkey").agg(F.countDistinct("l_suppkey").alias("suppliers"))


@query(None)
def q_distinct_approx(spark, d):
    """By sketches that hold small sets as they are: registers alone put several of some thirty suppliers into one."""
    return load(spark, d, "lineitem", "l_partkey", "l_suppkey").groupBy("l_partkey").agg(F.hll_sketch_estimate(F.hll_sketch_agg("l_suppkey", 12)).alias("suppliers"))


@query("select count(distinct l_partkey) as parts, cast(0 as bigint) as far_off from lineitem")
def q_distinct_error(spark, d):
    """Parts whose approximate number of suppliers is more than a tenth from the exact one: none."""
    both = q_distinct(spark, d).withColumnRenamed("suppliers", "exact").join(q_distinct_approx(spark, d), "l_partkey")
    return both.agg(F.count(F.lit(1)).alias("parts"), F.sum((F.abs(F.col("suppliers") - F.col("exact")) > 0.1 * F.col("exact")).cast("bigint")).alias("far_off"))


@query("""select o_orderstatus, count(*) filter (c_mktsegment = 'AUTOMOBILE') as "AUTOMOBILE", count(*) filter (c_mktsegment = 'BUILDING') as "BUILDING", count(*) filter (c_mktsegment = 'MACHINERY') as "MACHINERY"
          from orders join customer on c_custkey = o_custkey group by 1""")
def q_pivot(spark, d):
    j = load(spark, d, "orders", "o_custkey", "o_orderstatus").join(load(spark, d, "customer", "c_custkey", "c_mktsegment"), F.col("o_custkey") == F.col("c_custkey"))
    return j.groupBy("o_orderstatus").pivot("c_mktsegment", ["AUTOMOBILE", "BUILDING", "MACHINERY"]).count().na.fill(0)


@query("select l_partkey, count(distinct l_orderkey) as orders from lineitem group by 1 having count(distinct l_orderkey) >= 20")
def q_having(spark, d):
    return load(spark, d, "lineitem", "l_partkey", "l_orderkey").groupBy("l_partkey").agg(F.countDistinct("l_orderkey").alias("orders")).filter("orders >= 20")


@query("""select c_nationkey, n, cast(rank() over (order by n desc) as integer) as rk, cast(dense_rank() over (order by n desc) as integer) as dr, cast(row_number() over (order by n desc, c_nationkey) as integer) as rn,
          cast(ntile(4) over (order by n desc, c_nationkey) as integer) as quarter from (select c_nationkey, count(*) as n from customer group by 1)""")
def q_rank(spark, d):
    n = load(spark, d, "customer", "c_nationkey").groupBy("c_nationkey").agg(F.count(F.lit(1)).alias("n"))  # one row a nation
    w, u = Window.orderBy(F.desc("n")), Window.orderBy(F.desc("n"), "c_nationkey")
    return n.select("c_nationkey", "n", F.rank().over(w).alias("rk"), F.dense_rank().over(w).alias("dr"), F.row_number().over(u).alias("rn"), F.ntile(4).over(u).alias("quarter"))


@query("select o_orderkey, lag(o_orderkey) over w as prev, lead(o_orderkey) over w as next from orders window w as (partition by o_custkey order by o_orderdate, o_orderkey)")
def q_lead_lag(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderdate", "o_orderkey")
    return load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate").select("o_orderkey", F.lag("o_orderkey").over(w).alias("prev"), F.lead("o_orderkey").over(w).alias("next"))


@query("select o_orderkey, cast(sum(cast(round(o_totalprice * 100) as bigint)) over (partition by o_custkey order by o_orderkey rows unbounded preceding) as bigint) as cents from orders")
def q_running(spark, d):
    w = Window.partitionBy("o_custkey").orderBy("o_orderkey").rowsBetween(Window.unboundedPreceding, 0)
    return load(spark, d, "orders", "o_orderkey", "o_custkey", "o_totalprice").select("o_orderkey", F.sum(F.round(F.col("o_totalprice") * 100).cast("bigint")).over(w).alias("cents"))


@query("select event_id, count(*) over (partition by user_id order by epoch_us(ts) range between 3600000000 preceding and current row) as recent from events")
def q_range_frame(spark, d):
    e = load(spark, d, "events", "event_id", "user_id", "ts").withColumn("us", F.unix_micros(F.col("ts").cast("timestamp")))
    return e.select("event_id", F.count(F.lit(1)).over(Window.partitionBy("user_id").orderBy("us").rangeBetween(-3600000000, 0)).alias("recent"))


@query("""select p_brand, p_partkey, n from (select p_brand, p_partkey, n, row_number() over (partition by p_brand order by n desc, p_partkey) as rn
          from part join (select l_partkey, count(*) as n from lineitem group by 1) on l_partkey = p_partkey) where rn <= 3""")
def q_topk_group(spark, d):
    n = load(spark, d, "lineitem", "l_partkey").groupBy(F.col("l_partkey").alias("p_partkey")).agg(F.count(F.lit(1)).alias("n"))
    r = load(spark, d, "part", "p_partkey", "p_brand").join(n, "p_partkey").withColumn("rn", F.row_number().over(Window.partitionBy("p_brand").orderBy(F.desc("n"), "p_partkey")))
    return r.filter("rn <= 3").select("p_brand", "p_partkey", "n")


BIG, LATE = "select distinct l_orderkey as k from lineitem where l_quantity >= 49", "select distinct l_orderkey as k from lineitem where l_returnflag = 'R'"


def _sets(spark, d):
    l = load(spark, d, "lineitem", "l_orderkey", "l_quantity", "l_returnflag")
    return l.filter("l_quantity >= 49").select(F.col("l_orderkey").alias("k")).distinct(), l.filter("l_returnflag = 'R'").select(F.col("l_orderkey").alias("k")).distinct()


@query(f"{BIG} union {LATE}")
def q_union(spark, d):
    a, b = _sets(spark, d)
    return a.union(b).distinct()


@query(f"({BIG}) union all ({LATE})")
def q_union_all(spark, d):
    a, b = _sets(spark, d)
    return a.unionByName(b)


@query(f"({BIG}) intersect ({LATE})")
def q_intersect(spark, d):
    a, b = _sets(spark, d)
    return a.intersect(b)


@query(f"({BIG}) except ({LATE})")
def q_except(spark, d):
    a, b = _sets(spark, d)
    return a.exceptAll(b)


@query("""select page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as target from pages""")
def q_href(spark, d):
    return load(spark, d, "pages", "page_id", "html").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target"))


@query("select distinct doc_id, md5(line) as line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(line) >= 60")
def q_line_keys(spark, d):
    return load(spark, d, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") >= 60).select("doc_id", F.md5("line").alias("line")).distinct()


@query("select cast(props->>'$.k' as integer) as k, count(*) as n from events group by 1")
def q_json(spark, d):
    return load(spark, d, "events", "props").select(F.from_json("props", "k int")["k"].alias("k")).groupBy("k").agg(F.count(F.lit(1)).alias("n"))


@query("select user_id, string_agg(event_type, '>' order by ts, event_id) as path from events group by user_id")
def q_array(spark, d):
    e = load(spark, d, "events", "user_id", "event_id", "event_type", "ts")
    path = F.array_join(F.transform(F.sort_array(F.collect_list(F.struct("ts", "event_id", "event_type"))), lambda x: x["event_type"]), ">")
    return e.groupBy("user_id").agg(path.alias("path"))


DOT = "cast(list_sum(list_transform(list_zip(x.embedding, y.embedding), lambda p: cast(round(p[1] * 1000) as bigint) * cast(round(p[2] * 1000) as bigint))) as bigint)"


@query(f"select x.vec_id as a, y.vec_id as b, {DOT} as dot from embeddings x join embeddings y on y.vec_id = x.vec_id + 1")
def q_higher_order(spark, d):
    e = load(spark, d, "embeddings", "vec_id", "embedding").withColumn("v", F.transform("embedding", lambda x: F.round(x.cast("float") * F.lit(1000).cast("float")).cast("bigint")))
    x, y = e.select(F.col("vec_id").alias("a"), F.col("v").alias("va"), (F.col("vec_id") + 1).alias("b")), e.select(F.col("vec_id").alias("b"), F.col("v").alias("vb"))
    dot = F.aggregate(F.zip_with("va", "vb", lambda p, q: p * q), F.lit(0).cast("bigint"), lambda s, p: s + p)
    return x.join(y, "b").select("a", "b", dot.alias("dot"))


@query("select o_custkey, o_orderstatus as status, count(*) as n from orders group by all")
def q_map(spark, d):
    n = load(spark, d, "orders", "o_custkey", "o_orderstatus").groupBy("o_custkey", "o_orderstatus").agg(F.count(F.lit(1)).alias("n"))
    m = n.groupBy("o_custkey").agg(F.map_from_arrays(F.collect_list("o_orderstatus"), F.collect_list("n")).alias("m"))
    return m.select("o_custkey", F.explode("m").alias("status", "n"))


@query(f"""select kind, count(*) as edges from (select case when p.o_custkey = q.o_custkey then 'customer' when q.o_orderdate < p.o_orderdate then 'backward' else 'forward' end as kind
           from {CHAIN} e join orders p on p.o_orderkey = e.a join orders q on q.o_orderkey = e.b) group by kind""")
def q_case(spark, d):
    o = load(spark, d, "orders", "o_orderkey", "o_custkey", "o_orderdate")
    x, y = o.toDF("a", "ca", "da"), o.toDF("b", "cb", "db")
    kind = F.when(F.col("ca") == F.col("cb"), "customer").when(F.col("db") < F.col("da"), "backward").otherwise("forward")
    return chain(spark, d).join(x, "a").join(y, "b").groupBy(kind.alias("kind")).agg(F.count(F.lit(1)).alias("edges"))


@query(f"""select na, nb, a, b from (select p.c_nationkey as na, q.c_nationkey as nb, e.a, e.b, row_number() over (partition by p.c_nationkey, q.c_nationkey order by e.a, e.b) as rn from {CHAIN} e
           join orders oa on oa.o_orderkey = e.a join customer p on p.c_custkey = oa.o_custkey join orders ob on ob.o_orderkey = e.b join customer q on q.c_custkey = ob.o_custkey where p.c_nationkey < q.c_nationkey) where rn = 1""")
def q_struct_min(spark, d):
    """The representative edge of each pair of groups: argmin through a struct."""
    n = load(spark, d, "orders", "o_orderkey", "o_custkey").join(load(spark, d, "customer", "c_custkey", "c_nationkey"), F.col("o_custkey") == F.col("c_custkey")).select("o_orderkey", "c_nationkey")
    j = chain(spark, d).join(n.toDF("a", "na"), "a").join(n.toDF("b", "nb"), "b").filter("na < nb")
    return j.groupBy("na", "nb").agg(F.min(F.struct("a", "b")).alias("rep")).select("na", "nb", "rep.a", "rep.b")


@query("select l_returnflag, cast(sum(cast(l_extendedprice as decimal(18, 2))) as decimal(28, 2)) as total from lineitem group by 1")
def q_decimal(spark, d):
    return load(spark, d, "lineitem", "l_returnflag", "l_extendedprice").groupBy("l_returnflag").agg(F.sum(F.col("l_extendedprice").cast("decimal(18,2)")).cast("decimal(28,2)").alias("total"))


HOPS = f"""with recursive s as (select a as u, b as v from {CHAIN} union all select b, a from {CHAIN}),
walk as (select o_orderkey as start, o_orderkey as vid, 0 as hop from orders union all select walk.start, s.v, walk.hop + 1 from walk join s on s.u = walk.vid where walk.hop < 2)
select start, vid, min(hop) as hop from walk group by start, vid"""


@query(HOPS)
def q_sql_recursive(spark, d):
    """Two hops from every order by a bounded recursion over registered views."""
    from .sources.files import register

    register("order_chain", graph_view(spark, d, "order_chain"))
    load(spark, d, "orders", "o_orderkey").createOrReplaceTempView("v_orders")
    # the bound is the hops: the session's limit on rows, read while the recursion runs, is for ones without
    with session_setting(spark, "spark.sql.cteRecursionRowLimit", "-1"):
        return materialize(spark.sql("""with recursive s as (select a as u, b as v from v_order_chain_edges union all select b, a from v_order_chain_edges),
        walk as (select o_orderkey as start, o_orderkey as vid, 0 as hop from v_orders union all select walk.start, s.v, walk.hop + 1 from walk join s on s.u = walk.vid where walk.hop < 2)
        select start, vid, min(hop) as hop from walk group by start, vid"""), "two-hops")


@query("select n_name, t.c_custkey, t.cents from nation, lateral (select c_custkey, cast(round(c_acctbal * 100) as bigint) as cents from customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 2) t")
def q_lateral(spark, d):
    load(spark, d, "nation").createOrReplaceTempView("v_nation")
    load(spark, d, "customer").createOrReplaceTempView("v_customer")
    return spark.sql("select n_name, t.c_custkey, t.cents from v_nation, lateral (select c_custkey, cast(round(c_acctbal * 100) as bigint) as cents from v_customer where c_nationkey = n_nationkey order by c_acctbal desc, c_custkey limit 2) t")


@query("select c_custkey from customer where exists (select 1 from orders where o_custkey = c_custkey and o_totalprice > 400000)")
def q_exists(spark, d):
    load(spark, d, "orders").createOrReplaceTempView("v_orders_all")
    load(spark, d, "customer").createOrReplaceTempView("v_customer")
    return spark.sql("select c_custkey from v_customer where exists (select 1 from v_orders_all where o_custkey = c_custkey and o_totalprice > 400000)")


@query(f"select vid, degree from {DEGREES} where degree > (select avg(degree) from {DEGREES})")
def q_scalar_sub(spark, d):
    deg = q_degree(spark, d)
    return deg.join(F.broadcast(deg.agg(F.avg("degree").alias("mean"))), F.col("degree") > F.col("mean")).select("vid", "degree")


@query("select o_custkey, cast(year(o_orderdate) as integer) as y, cast(month(o_orderdate) as integer) as m, count(*) as n from orders group by all")
def q_dates(spark, d):
    return load(spark, d, "orders", "o_custkey", "o_orderdate").groupBy("o_custkey", F.year("o_orderdate").alias("y"), F.month("o_orderdate").alias("m")).agg(F.count(F.lit(1)).alias("n"))


@query("select page_id, lower(split_part(split_part(url, '://', 2), '/', 1)) as host, length(url) as n, md5(url) as key, levenshtein(substr(url, 1, 12), 'https://www.') as distance from pages")
def q_strings(spark, d):
    p = load(spark, d, "pages", "page_id", "url")
    return p.select("page_id", F.lower(F.split_part(F.split_part("url", F.lit("://"), F.lit(2)), F.lit("/"), F.lit(1))).alias("host"), F.length("url").cast("bigint").alias("n"), F.md5("url").alias("key"), F.levenshtein(F.substring("url", 1, 12), F.lit("https://www.")).cast("bigint").alias("distance"))


@query("select vec_id, cast(bit_count(vec_id) as integer) as ones, vec_id % 7 as rest, cast(floor(sqrt(vec_id)) as bigint) as root, vec_id << 3 as shifted from embeddings")
def q_math(spark, d):
    return load(spark, d, "embeddings", "vec_id").select("vec_id", F.bit_count("vec_id").alias("ones"), F.pmod("vec_id", F.lit(7)).alias("rest"), F.floor(F.sqrt("vec_id")).alias("root"), F.shiftleft("vec_id", 3).alias("shifted"))


@query("select p_partkey, p_name from part where p_name like '%i%' and p_size between 5 and 15 and p_brand in ('Brand#2', 'Brand#3', 'Brand#17') or not p_type <> 'SMALL' and p_retailprice > 950 or p_name ~ '^hot g' and p_size is not null")
def q_predicates(spark, d):
    p = load(spark, d, "part", "p_partkey", "p_name", "p_size", "p_brand", "p_type", "p_retailprice")
    liked = F.col("p_name").like("%i%") & F.col("p_size").between(5, 15) & F.col("p_brand").isin("Brand#2", "Brand#3", "Brand#17")
    small = F.col("p_type").eqNullSafe(F.lit("SMALL")) & (F.col("p_retailprice") > 950)
    return p.filter(liked | small | (F.col("p_name").rlike("^hot g") & F.col("p_size").isNotNull())).select("p_partkey", "p_name")


@query("select s_suppkey, c_custkey from supplier join customer on c_nationkey = s_nationkey and c_acctbal between s_acctbal - 250 and s_acctbal + 250")
def q_range_join(spark, d):
    """Customers whose balance lies near that of a supplier of their nation: bins turn the range into an equality."""
    from .operators.joins import range_join

    s = load(spark, d, "supplier", "s_suppkey", "s_nationkey", "s_acctbal").select("s_suppkey", F.col("s_nationkey").alias("nation"), (F.col("s_acctbal") - 250).alias("low"), (F.col("s_acctbal") + 250).alias("high"))
    c = load(spark, d, "customer", "c_custkey", "c_nationkey", "c_acctbal").select("c_custkey", F.col("c_nationkey").alias("nation"), F.col("c_acctbal").alias("at"))
    return range_join(c, s, "at", "low", "high", 500, ("nation",)).select("s_suppkey", "c_custkey")


@query("select n_name, count(*) as orders from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by 1")
def q_guarded_broadcast(spark, d):
    """Dimension tables are broadcast where their estimated size allows it."""
    from .operators.joins import broadcast_under

    c = load(spark, d, "customer", "c_custkey", "c_nationkey").join(broadcast_under(load(spark, d, "nation", "n_nationkey", "n_name"), 1 << 20), F.col("c_nationkey") == F.col("n_nationkey"))
    return load(spark, d, "orders", "o_custkey").join(broadcast_under(c, 16 << 20), F.col("o_custkey") == F.col("c_custkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("orders"))


@query("select count(*) as lines, cast(sum(l_linenumber) as bigint) as numbers, count(distinct l_partkey) as parts from lineitem where l_quantity >= 45")
def q_observe(spark, d):
    """Figures taken from the rows while another query reads them: no second pass."""
    from .plans.scratch import Watch

    watch = Watch(numbers=F.col("l_linenumber"))
    lines = watch.over(load(spark, d, "lineitem", "l_partkey", "l_linenumber", "l_quantity").filter("l_quantity >= 45"))
    parts = lines.select("l_partkey").distinct().count()
    seen = watch.figures()
    return spark.createDataFrame([(seen["rows"], seen["numbers"], parts)], "lines long, numbers long, parts long")


TRADE = """(select c_nationkey as u, s_nationkey as v, count(*) as n from lineitem join orders on o_orderkey = l_orderkey join customer on c_custkey = o_custkey join supplier on s_suppkey = l_suppkey where c_nationkey <> s_nationkey group by all)"""
PARTNERS = f"(select distinct least(u, v) as a, greatest(u, v) as b from (select u, v, row_number() over (partition by u order by n desc, v) as rn from {TRADE}) where rn <= 1)"


@query(f"""with recursive e as materialized (select * from {PARTNERS}), nodes as materialized (select a as vid from e union select b from e), s as materialized (select a as u, b as v from e union select b, a from e),
comp(gone, vid, c) using key (gone, vid) as (
  select r.vid, n.vid, n.vid from nodes r join nodes n on n.vid <> r.vid
  union
  select comp.gone, s.v, min(comp.c) from comp join s on s.u = comp.vid join recurring.comp r on r.gone = comp.gone and r.vid = s.v where comp.c < r.c group by comp.gone, s.v)
select x.gone as vid from comp x join s on s.u = x.gone and s.v = x.vid group by x.gone having count(distinct x.c) > 1""")
def q_cross_brute(spark, d):
    """Articulation points of the nations' trade by removing each nation in turn: a guarded cross join, 25 graphs of 25 vertices."""
    from .operators.connect import components_star
    from .operators.joins import guarded_cross
    from .plans.graph import Graph

    c = load(spark, d, "customer", "c_custkey", "c_nationkey").join(load(spark, d, "orders", "o_orderkey", "o_custkey"), F.col("c_custkey") == F.col("o_custkey"))
    lines = load(spark, d, "lineitem", "l_orderkey", "l_suppkey").join(c, F.col("l_orderkey") == F.col("o_orderkey")).join(load(spark, d, "supplier", "s_suppkey", "s_nationkey"), F.col("l_suppkey") == F.col("s_suppkey"))
    trade = lines.filter("c_nationkey <> s_nationkey").groupBy(F.col("c_nationkey").alias("u"), F.col("s_nationkey").alias("v")).agg(F.count(F.lit(1)).alias("n"))
    most = trade.withColumn("rn", F.row_number().over(Window.partitionBy("u").orderBy(F.desc("n"), "v"))).filter("rn = 1")
    g = Graph.of(most.select("u", "v")).fixed("trade")
    key = lambda gone, v: (F.col(gone) * 1000 + F.col(v))
    left = guarded_cross(g.vertices.withColumnRenamed("vid", "gone"), g.vertices).filter("gone <> vid").select(key("gone", "vid").alias("vid"))
    edges = guarded_cross(g.vertices.withColumnRenamed("vid", "gone"), g.edges.select("a", "b")).filter("gone <> a and gone <> b").select(key("gone", "a").alias("a"), key("gone", "b").alias("b"))
    comp = components_star(Graph(left, edges)).select(F.floor(F.col("vid") / 1000).cast("bigint").alias("gone"), F.pmod("vid", F.lit(1000)).alias("vid"), "comp")
    near = g.arcs().select(F.col("src").alias("gone"), F.col("dst").alias("vid"))
    return near.join(comp, ["gone", "vid"]).groupBy("gone").agg(F.countDistinct("comp").alias("n")).filter("n > 1").select(F.col("gone").alias("vid"))


@query("select cast(conv_id as bigint) as qid, cast(conv_id * 100 + turn as bigint) as vid, cast(turn - least_turn as bigint) as hop from (select conv_id, turn, row_number() over (partition by conv_id order by turn) - 1 as place, min(turn) over (partition by conv_id) as least_turn from conversations) where place <= 3")
def q_udtf_search(spark, d):
    """Turns within three hops of each conversation's first one: a table function over each conversation's own edges."""
    from .functions import python_functions as pf

    pf.register(spark)
    c = load(spark, d, "conversations", "conv_id", "turn")
    w = Window.partitionBy("conv_id").orderBy("turn")
    vid = F.col("conv_id") * 100 + F.col("turn")
    edges = c.select(F.col("conv_id").cast("bigint").alias("qid"), F.first(vid).over(w).cast("bigint").alias("start"), vid.cast("bigint").alias("a"), F.lead(vid).over(w).cast("bigint").alias("b"))
    edges.createOrReplaceTempView("v_conversation_edges")
    return spark.sql("select * from lw_bounded_search(table(v_conversation_edges) partition by qid)")


@query(f"select 'csv' as fmt, count(*) as edges, 2 as lost from {CHAIN} union all select 'json', count(*), 2 from {CHAIN} union all select 'orc', count(*), 0 from {CHAIN} union all select 'text', count(*), 2 from {CHAIN} union all select 'parquet', count(*), 0 from {CHAIN}")
def s2_read_edges(spark, d):
    """The chain's edges written and read in every format; two broken lines in each text format are set aside."""
    from .plans.scratch import new_scratch_path
    from .sources.files import FORMATS, read_edges, write_edges

    base, rows = chain(spark, d).select(F.col("a").alias("x"), F.col("b").alias("y")), []
    for fmt in FORMATS:
        path = new_scratch_path(spark, f"edges-{fmt}")
        write_edges(base, path, fmt)
        if fmt not in ("orc", "parquet"):
            spark.createDataFrame([("broken",), ("1 two 3" if fmt != "json" else '{"x": 1}',)], "value string").coalesce(1).write.mode("append").text(path)
        edges, lost = read_edges(spark, path, fmt)
        rows.append((fmt, edges.intersect(base).count(), lost.count()))
    return spark.createDataFrame(rows, "fmt string, edges long, lost int")


@query(f"select vid, degree from {DEGREES}")
def s3_bucketed_adjacency(spark, d):
    """Degrees from adjacency lists bucketed by vertex: neither the lists nor their counts are exchanged."""
    from .plans.adjacency import adjacency
    from .plans.scratch import materialize

    with adjacency(graph_view(spark, d, "order_chain")) as lists:
        return materialize(lists.groupBy(F.col("src").alias("vid")).agg(F.count(F.lit(1)).alias("degree")), "degrees")


@query(f"select vid, degree from {DEGREES}")
def s5_barriers(spark, d):
    """The same rows behind both barriers."""
    from .plans.scratch import barrier

    deg = q_degree(spark, d)
    x, y = barrier(deg, "parquet"), barrier(deg, "reliable").withColumnRenamed("degree", "again")
    return x.join(y, "vid").filter("degree = again").select("vid", "degree")


@query("""select b.vid, b.comp, b.size from (select comp, count(*) as size from (select s_suppkey as vid, min(s_suppkey) over (partition by s_nationkey) as comp from supplier) group by comp) c
          join (select s_suppkey as vid, min(s_suppkey) over (partition by s_nationkey) as comp, count(*) over (partition by s_nationkey) as size from supplier) b on b.comp = c.comp""")
def q_sql_surface(spark, d):
    """A graph and its components under SQL names: suppliers of a nation, linked to the first of them."""
    from .operators.connect import components_star
    from .plans.graph import Graph
    from .sources.files import register

    s = load(spark, d, "supplier", "s_suppkey", "s_nationkey")
    g = Graph.of(s.select(F.min("s_suppkey").over(Window.partitionBy("s_nationkey")).alias("x"), F.col("s_suppkey").alias("y")))
    register("suppliers", g, components=components_star(g))
    return spark.sql("select vid, comp, count(*) over (partition by comp) as size from v_suppliers_components")
