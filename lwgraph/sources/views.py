"""Graph views over the given tables, by name.

A view is a plan over pruned scans, stated once as SQL that any engine can run; the
placeholders in braces are the tables.  Keys of mixed kinds are kind * 10**12 + key.
"""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..plans.graph import Graph

TABLES = ("region", "nation", "customer", "supplier", "part", "orders", "lineitem", "events", "documents", "embeddings", "pages", "benchmark", "labels", "conversations")
K = 10**12


def load(spark: SparkSession, sf_dir: str, name: str, *cols: str) -> DataFrame:
    """One table, pruned to the named columns."""
    df = spark.read.parquet(f"{sf_dir}/{name}.parquet")
    return df.select(*cols) if cols else df


_CHAIN = "select {key} as x, lead({key}) over (partition by {group} order by {key}) as y from {source}"


def _chain(key: str, group: str, source: str) -> str:
    return f"select {key} as x, lead({key}) over (partition by {group} order by {key}) as y from {source}"


# name -> (edge query, vertex query or None); both run unchanged in Spark SQL and in DuckDB once the braces are filled
VIEWS: dict[str, tuple[str, str | None]] = {
    "geo_tree": (
        f"""select {1 * K} + n_regionkey as x, {2 * K} + n_nationkey as y from {{nation}}
            union all select {2 * K} + s_nationkey, {3 * K} + s_suppkey from {{supplier}}
            union all select {2 * K} + c_nationkey, {4 * K} + c_custkey from {{customer}}""",
        f"""select {1 * K} + r_regionkey as vid from {{region}} union all select {2 * K} + n_nationkey from {{nation}}
            union all select {3 * K} + s_suppkey from {{supplier}} union all select {4 * K} + c_custkey from {{customer}}"""),
    "customer_order": (
        f"select {4 * K} + o_custkey as x, {5 * K} + o_orderkey as y from {{orders}}",
        f"select {4 * K} + c_custkey as vid from {{customer}} union all select {5 * K} + o_orderkey from {{orders}}"),
    "part_supplier": (f"select {6 * K} + l_partkey as x, {3 * K} + l_suppkey as y from {{lineitem}}", None),
    "part_supplier_slice": (f"select {6 * K} + l_partkey as x, {3 * K} + l_suppkey as y from {{lineitem}} where l_returnflag = 'R' and l_quantity >= 48", None),
    "order_part": (f"select {5 * K} + l_orderkey as x, {6 * K} + l_partkey as y from {{lineitem}}", None),
    "order_chain": (
        _chain("o_orderkey", "o_custkey", "{orders}") + " union all "
        + _chain("l_orderkey", "l_partkey", "(select distinct l_partkey, l_orderkey from {lineitem} where l_quantity >= 45) as q"),
        "select o_orderkey as vid from {orders}"),
    "order_fragments": (_chain("l_orderkey", "l_partkey", "(select distinct l_partkey, l_orderkey from {lineitem} where l_quantity >= 40 and l_returnflag = 'R') as q"), None),
    "event_paths": ("select event_id as x, lead(event_id) over (partition by user_id order by ts, event_id) as y from {events}", "select event_id as vid from {events}"),
    "event_mesh": (
        _chain("event_id", "user_id", "{events}") + " union all "
        + _chain("event_id", "k, event_type", "(select event_id, event_type, substr(props, instr(props, ':') + 1) as k from {events}) as q"),
        "select event_id as vid from {events}"),
    "conversation_chain": (
        "select conv_id * 100 + turn as x, lead(conv_id * 100 + turn) over (partition by conv_id order by turn) as y from {conversations}",
        "select conv_id * 100 + turn as vid from {conversations}"),
    "doc_copies": ("select min(doc_id) over (partition by md5(text)) as x, doc_id as y from {documents}", "select doc_id as vid from {documents}"),
}


def _filled(query: str, names: dict[str, str] | None = None) -> str:
    for t in TABLES:
        query = query.replace("{" + t + "}", (names or {}).get(t, t))
    return query


def edge_sql(name: str) -> str:
    """The view's pairs (x, y) in plain SQL over the registered tables."""
    return _filled(SQL_ONLY[name] if name in SQL_ONLY else VIEWS[name][0])


def vertex_sql(name: str) -> str | None:
    query = VIEWS[name][1] if name in VIEWS else VERTEX_SQL_ONLY.get(name)
    return _filled(query) if query else None


# views whose texts need functions that the engines name differently
SQL_ONLY = {
    "page_links": f"""select {7 * K} + page_id as x, {8 * K} + dense_rank() over (order by target) as y
                      from (select page_id, unnest(regexp_extract_all(html, 'href="([^"]*)"', 1)) as target from pages)""",
    "doc_lines": """select min(doc_id) over (partition by md5(line)) as x, doc_id as y
                    from (select distinct doc_id, line from (select doc_id, unnest(string_split(text, chr(10))) as line from documents) where length(line) >= 60)""",
}
SQL_ONLY["embedding_nn"] = """with v as (select vec_id, list_transform(embedding, lambda x: cast(round(x * cast(1000 as float)) as bigint)) as q from embeddings),
                    s as (select a.vec_id as x, b.vec_id as y, list_sum(list_transform(list_zip(a.q, b.q), lambda p: p[1] * p[2])) as score from v a join v b on a.vec_id <> b.vec_id)
                    select x, y from (select x, y, row_number() over (partition by x order by score desc, y) as n from s) where n <= 2"""
VERTEX_SQL_ONLY = {"embedding_nn": "select vec_id as vid from embeddings", "page_links": f"select {7 * K} + page_id as vid from pages", "doc_lines": "select doc_id as vid from documents"}


def _sql(spark: SparkSession, sf_dir: str, query: str) -> DataFrame:
    used = {t: load(spark, sf_dir, t) for t in TABLES if "{" + t + "}" in query}
    return spark.sql(query, **used)


def number_strings(values: DataFrame, column: str, base: int) -> DataFrame:
    """(column, vid): strings numbered from 1 in binary order, by range partitions and their offsets."""
    from ..operators.trees import global_index

    return global_index(values.select(column).distinct(), [column], "n").select(column, (F.col("n") + base + 1).alias("vid"))


def graph_view(spark: SparkSession, sf_dir: str, name: str, *, p: float | None = None, seed: int = 0, month: tuple[int, int] | None = None) -> Graph:
    """The named view; ``percolation`` takes p and seed, ``order_month`` a (year, month)."""
    if name == "percolation":
        base = graph_view(spark, sf_dir, "event_mesh")
        return Graph(base.vertices, base.edges.filter(hash_below(p, F.lit(seed), F.col("a"), F.col("b"))))
    if name == "order_month":
        base = graph_view(spark, sf_dir, "order_chain")
        dates = load(spark, sf_dir, "orders", "o_orderkey", "o_orderdate").filter((F.year("o_orderdate") == month[0]) & (F.month("o_orderdate") == month[1])).select(F.col("o_orderkey").alias("vid"))
        edges = base.edges.join(dates, base.edges["a"] == dates["vid"], "left_semi")
        return Graph(dates.unionByName(edges.select(F.col("b").alias("vid"))).distinct(), edges)
    if name == "page_links":
        hrefs = load(spark, sf_dir, "pages", "page_id", "html").select("page_id", F.explode(F.regexp_extract_all("html", F.lit('href="([^"]*)"'), F.lit(1))).alias("target"))
        numbers = number_strings(hrefs, "target", 8 * K)
        pairs = hrefs.join(numbers, "target").select((F.col("page_id") + 7 * K).alias("x"), F.col("vid").alias("y"))
        return Graph.of(pairs, load(spark, sf_dir, "pages", "page_id").select((F.col("page_id") + 7 * K).alias("vid")))
    if name == "doc_lines":
        lines = load(spark, sf_dir, "documents", "doc_id", "text").select("doc_id", F.explode(F.split("text", "\n")).alias("line")).filter(F.length("line") >= 60).select("doc_id", F.md5("line").alias("line")).distinct()
        firsts = lines.groupBy("line").agg(F.min("doc_id").alias("x"), F.count(F.lit(1)).alias("n")).filter("n > 1").select("line", "x")
        return Graph.of(lines.join(firsts, "line").select("x", F.col("doc_id").alias("y")), load(spark, sf_dir, "documents", "doc_id"))
    if name == "embedding_nn":
        return Graph.of(nearest_vectors(load(spark, sf_dir, "embeddings", "vec_id", "embedding")).select(F.col("vec_id").alias("x"), F.col("near").alias("y")), load(spark, sf_dir, "embeddings", "vec_id"))
    edges, vertices = VIEWS[name]
    return Graph.of(_sql(spark, sf_dir, edges), _sql(spark, sf_dir, vertices) if vertices else None)


def nearest_vectors(vectors: DataFrame, k: int = 2, scale: int = 1000, block: int = 2048) -> DataFrame:
    """(vec_id, near): the k others of largest whole-number inner product, ties to smaller ids; every vector against all, block by block."""
    import numpy as np
    import pyarrow as pa
    from pyspark.sql import Window

    whole = vectors.select("vec_id", F.transform("embedding", lambda x: F.round(x.cast("float") * F.lit(scale).cast("float")).cast("bigint")).alias("v"))
    blocks = max(1, -(-whole.count() // block))
    part = F.pmod(F.xxhash64("vec_id"), F.lit(blocks)).cast("int")
    every = F.explode(F.sequence(F.lit(0), F.lit(blocks - 1)))
    asked = whole.select(part.alias("mine"), every.alias("theirs"), "vec_id", "v")
    rows = whole.select(every.alias("mine"), part.alias("theirs"), "vec_id", "v")

    def meet(left: pa.Table, right: pa.Table) -> pa.Table:
        dense = lambda t: np.stack([np.asarray(v, np.float64) for v in t.column("v").to_pylist()]) if t.num_rows else np.zeros((0, 1))
        mine, ids = left.column("vec_id").to_numpy(), right.column("vec_id").to_numpy()
        out = [np.zeros((0, 3), np.int64)]
        if len(mine) and len(ids):
            scores = (dense(left) @ dense(right).T).astype(np.int64)
            for me, row in zip(mine, scores, strict=True):
                best = [j for j in np.lexsort((ids, -row))[: k + 1] if ids[j] != me][:k]
                out.append(np.stack([np.full(len(best), me), ids[best], row[best]], 1))
        a = np.concatenate(out)
        return pa.table({"vec_id": pa.array(a[:, 0]), "near": pa.array(a[:, 1]), "score": pa.array(a[:, 2])})

    met = asked.groupBy("mine", "theirs").cogroup(rows.groupBy("mine", "theirs")).applyInArrow(meet, "vec_id long, near long, score long")
    rank = F.row_number().over(Window.partitionBy("vec_id").orderBy(F.desc("score"), "near"))
    return met.withColumn("rank", rank).filter(F.col("rank") <= k).select("vec_id", "near")


def hash_text(*parts):
    """First eight hex digits of md5('p1:p2:...'), the same in every engine."""
    return F.substring(F.md5(F.concat_ws(":", *[p.cast("string") for p in parts])), 1, 8)


def hash_threshold(p: float) -> str:
    return f"{min(2**32 - 1, int(p * 2**32)):08x}"


def hash_below(p: float, *parts):
    return hash_text(*parts) < F.lit(hash_threshold(p)) if p < 1 else F.lit(True)
