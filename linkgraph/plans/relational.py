"""Relational operators that users of the methods need around them, with their SQL twins.

Each entry is (function of (spark, sf_dir), SQL text).
"""

from __future__ import annotations

import pandas as pd
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def projection(spark, d):
    return _t(spark, d, "lineitem").select("l_orderkey", F.col("l_quantity").cast("int").alias("units"), (F.col("l_extendedprice").cast("decimal(18,2)") * (1 - F.col("l_discount").cast("decimal(4,2)"))).cast("decimal(18,4)").alias("net"))


def predicates(spark, d):
    o = _t(spark, d, "orders")
    return o.filter((F.col("o_orderdate") >= "1995-01-01") & F.col("o_orderstatus").isin("O", "F") & F.col("o_orderpriority").rlike("^[12]-")).groupBy("o_orderstatus").agg(F.count(F.lit(1)).alias("n"))


def broadcast_join(spark, d):
    c, n = _t(spark, d, "customer"), _t(spark, d, "nation")
    return c.join(F.broadcast(n), F.col("c_nationkey") == F.col("n_nationkey")).groupBy("n_name").agg(F.count(F.lit(1)).alias("n_customers"))


def merge_join(spark, d):
    o, l = _t(spark, d, "orders"), _t(spark, d, "lineitem").select("l_orderkey", "l_quantity")
    return o.join(l.hint("merge"), F.col("o_orderkey") == F.col("l_orderkey")).groupBy("o_orderstatus").agg(F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("units"))


def outer_join(spark, d):
    left, right = _t(spark, d, "documents").select("doc_id"), _t(spark, d, "labels").select("doc_id", "toxic")
    return left.join(right, "doc_id", "full").groupBy("toxic").agg(F.count(F.lit(1)).alias("n"))


def semi_anti(spark, d):
    docs, labels = _t(spark, d, "documents"), _t(spark, d, "labels")
    a = docs.join(labels, "doc_id", "left_semi").agg(F.count(F.lit(1)).alias("n")).select(F.lit("labelled").alias("kind"), "n")
    return a.union(docs.join(labels, "doc_id", "left_anti").agg(F.count(F.lit(1)).alias("n")).select(F.lit("unlabelled"), "n"))


def theta_join(spark, d):
    r = _t(spark, d, "nation")
    a, b = r.select(F.col("n_nationkey").alias("a"), F.col("n_regionkey").alias("ra")), r.select(F.col("n_nationkey").alias("b"), F.col("n_regionkey").alias("rb"))
    return a.join(F.broadcast(b), (F.col("a") < F.col("b")) & (F.col("ra") == F.col("rb"))).select("a", "b")


def range_join(spark, d):
    """Events of a user within a day after each purchase, by day buckets instead of all pairs."""
    day = lambda c: F.floor(F.unix_seconds(F.col(c).cast("timestamp")) / 86400)
    e = _t(spark, d, "events").select("event_id", "user_id", "ts", "event_type", day("ts").alias("bucket"))
    bought = e.filter("event_type = 'purchase'").select(F.col("event_id").alias("purchase_id"), F.col("user_id").alias("buyer"), F.col("ts").alias("at"), F.explode(F.array("bucket", F.col("bucket") + 1)).alias("day"))
    hit = bought.join(e, (F.col("buyer") == F.col("user_id")) & (F.col("day") == F.col("bucket"))).filter("ts > at and ts < at + interval 1 day")
    return hit.groupBy("purchase_id").agg(F.count(F.lit(1)).alias("n"))


def asof_join(spark, d):
    """The latest event at or before each event of kind "purchase" of a user, without a join."""
    e = _t(spark, d, "events").select("event_id", "user_id", "ts", "event_type", "value")
    w = Window.partitionBy("user_id").orderBy("ts", "event_id").rowsBetween(Window.unboundedPreceding, -1)
    last = F.last(F.when(F.col("event_type") != "purchase", F.col("event_id")), ignorenulls=True).over(w)
    return e.withColumn("before_id", last).filter("event_type = 'purchase'").select("event_id", "before_id")


def lateral_topk(spark, d):
    """The two dearest orders of each customer of the first nation."""
    o = _t(spark, d, "orders").select("o_orderkey", "o_custkey", "o_totalprice")
    c = _t(spark, d, "customer").filter("c_nationkey = 0").select("c_custkey")
    w = Window.partitionBy("o_custkey").orderBy(F.desc("o_totalprice"), "o_orderkey")
    return c.join(o, F.col("c_custkey") == F.col("o_custkey")).withColumn("r", F.row_number().over(w)).filter("r <= 2").select("c_custkey", "o_orderkey", F.col("r").cast("int").alias("r"))


def filtered_aggregates(spark, d):
    l = _t(spark, d, "lineitem")
    return l.groupBy("l_returnflag").agg(F.count(F.lit(1)).alias("n"), F.count_if(F.col("l_discount") > 0.05).alias("n_rebate"), F.count_distinct("l_suppkey").alias("n_supp"), F.sum(F.col("l_quantity").cast("decimal(18,2)")).alias("units"))


def cube(spark, d):
    return _t(spark, d, "lineitem").cube("l_returnflag", "l_linestatus").agg(F.count(F.lit(1)).alias("n"))


def rollup(spark, d):
    return _t(spark, d, "orders").rollup("o_orderstatus", "o_orderpriority").agg(F.count(F.lit(1)).alias("n"))


def windows(spark, d):
    w = Window.partitionBy("user_id").orderBy("ts", "event_id")
    e = _t(spark, d, "events")
    return e.select("event_id", F.row_number().over(w).alias("n"), F.lag("event_id").over(w).alias("prev_id"), F.lead("event_id").over(w).alias("next_id"), F.ntile(4).over(w).alias("quarter"))


def set_operations(spark, d):
    c, s = _t(spark, d, "customer").select(F.col("c_nationkey").alias("k")), _t(spark, d, "supplier").select(F.col("s_nationkey").alias("k"))
    tag = lambda df, what: df.agg(F.count(F.lit(1)).alias("n")).select(F.lit(what).alias("what"), "n")
    return tag(c.union(s), "union all").union(tag(c.union(s).distinct(), "union")).union(tag(c.intersect(s), "intersect")).union(tag(c.exceptAll(s), "except all")).union(tag(c.intersectAll(s), "intersect all"))


def pivot(spark, d):
    return _t(spark, d, "orders").groupBy("o_orderstatus").pivot("o_orderpriority", ["1-URGENT", "2-HIGH"]).agg(F.count(F.lit(1))).select("o_orderstatus", F.coalesce("1-URGENT", F.lit(0)).alias("urgent"), F.coalesce("2-HIGH", F.lit(0)).alias("high"))


def strings(spark, d):
    p = _t(spark, d, "part")
    return p.select("p_partkey", F.upper("p_name").alias("up"), F.length("p_name").alias("len"), F.substring("p_name", 1, 4).alias("head"), F.md5("p_name").alias("digest"), F.levenshtein("p_name", "p_brand").alias("lev"))


def dates(spark, d):
    o = _t(spark, d, "orders")
    return o.groupBy(F.year("o_orderdate").alias("y"), F.quarter("o_orderdate").alias("q")).agg(F.count(F.lit(1)).alias("n"))


def json_fields(spark, d):
    e = _t(spark, d, "events")
    return e.groupBy(F.get_json_object("props", "$.k").cast("int").alias("k")).agg(F.count(F.lit(1)).alias("n"))


def html_titles(spark, d):
    p = _t(spark, d, "pages")
    return p.select("page_id", F.regexp_extract("html", "<title>(.*?)</title>", 1).alias("title"))


def arrays(spark, d):
    v = _t(spark, d, "embeddings")
    return v.select("vec_id", F.size("embedding").alias("dim"), F.size(F.filter("embedding", lambda x: x > 0)).alias("positive"))


def top_rows(spark, d):
    return _t(spark, d, "orders").orderBy(F.desc("o_totalprice"), "o_orderkey").limit(100).select("o_orderkey")


def hash_sample(spark, d):
    from linkgraph.functions.draws import u52

    return _t(spark, d, "orders").filter(u52(42, "sample", F.col("o_orderkey")) < 0.1).select("o_orderkey")


def tumbling(spark, d):
    return _t(spark, d, "events").groupBy(F.window(F.col("ts").cast("timestamp"), "1 hour").alias("w"), "event_type").agg(F.count(F.lit(1)).alias("n")).select(F.unix_seconds("w.start").alias("start"), "event_type", "n")


def approximate(spark, d):
    """Sketches within their stated errors of the exact figures: distinct values, medians, frequent values."""
    line = _t(spark, d, "lineitem")
    exact = line.agg(F.count_distinct("l_orderkey").alias("n"), F.expr("percentile(l_extendedprice, 0.5)").alias("m"))
    rough = line.agg(
        F.approx_count_distinct("l_orderkey", 0.02).alias("a"), F.hll_sketch_estimate(F.hll_sketch_agg("l_orderkey")).alias("h"),
        F.percentile_approx("l_extendedprice", 0.5, 10_000).alias("p"), F.expr("kll_sketch_get_quantile_double(kll_sketch_agg_double(l_extendedprice), 0.5D)").alias("k"),
    )
    both = exact.crossJoin(rough)  # one row each
    near = lambda c, to, by: (F.abs(F.col(c) / F.col(to) - 1) <= by)
    return both.select(near("a", "n", 0.06).alias("distinct_ok"), near("h", "n", 0.06).alias("sketch_ok"), near("p", "m", 0.01).alias("median_ok"), near("k", "m", 0.06).alias("quantiles_ok"))


def arrow_function(spark, d):
    """Vector lengths by a function over Arrow columns."""
    import pyarrow as pa
    import pyarrow.compute as pc

    @F.pandas_udf("double")
    def length(v: pd.Series) -> pd.Series:
        return v.map(lambda x: float(sum(float(y) * float(y) for y in x)) ** 0.5)

    def squares(batches):
        for b in batches:
            v = b.column("embedding")
            flat = pc.cast(v.flatten(), pa.float64())
            sums = pa.TableGroupBy(pa.table({"i": pc.list_parent_indices(v), "x": pc.multiply(flat, flat)}), "i").aggregate([("x", "sum")]).sort_by("i")
            yield pa.RecordBatch.from_arrays([b.column("vec_id"), pc.sqrt(sums.column("x_sum")).combine_chunks()], names=["vec_id", "size"])

    v = _t(spark, d, "embeddings").select("vec_id", "embedding")
    by_arrow = v.mapInArrow(squares, "vec_id long, size double")
    return by_arrow.join(v.select("vec_id", length("embedding").alias("other")), "vec_id").select("vec_id", F.round("size", 4).alias("size"), (F.abs(F.col("size") - F.col("other")) < 1e-9).alias("same"))


def grouped_function(spark, d):
    """Spread of balances by nation with an aggregate function over Arrow batches."""

    @F.pandas_udf("double")
    def spread(v: pd.Series) -> float:
        return float(v.max() - v.min())

    return _t(spark, d, "customer").groupBy("c_nationkey").agg(F.round(spread("c_acctbal"), 2).alias("spread"))


def table_function(spark, d):
    """Words of names with their places, by a table function in a lateral join."""

    @F.udtf(returnType="pos int, word string")
    class Words:
        def eval(self, text: str):
            for k, w in enumerate((text or "").split(" ")):
                yield k, w

    spark.udtf.register("linkgraph_words", Words)
    _t(spark, d, "part").select("p_partkey", "p_name").createOrReplaceTempView("linkgraph_parts")
    return spark.sql("SELECT p_partkey, w.pos, w.word FROM linkgraph_parts, LATERAL linkgraph_words(p_name) w")


_DAY = "CAST(floor(epoch({c}) / 86400) AS BIGINT)"

QUERIES: dict = {
    "rel_projection": (projection, "SELECT l_orderkey, CAST(l_quantity AS INT) AS units, CAST(CAST(l_extendedprice AS DECIMAL(18,2)) * (1 - CAST(l_discount AS DECIMAL(4,2))) AS DECIMAL(18,4)) AS net FROM lineitem"),
    "rel_predicates": (predicates, "SELECT o_orderstatus, count(*) AS n FROM orders WHERE o_orderdate >= TIMESTAMP '1995-01-01' AND o_orderstatus IN ('O', 'F') AND regexp_matches(o_orderpriority, '^[12]-') GROUP BY 1"),
    "rel_broadcast_join": (broadcast_join, "SELECT n_name, count(*) AS n_customers FROM customer JOIN nation ON c_nationkey = n_nationkey GROUP BY 1"),
    "rel_merge_join": (merge_join, "SELECT o_orderstatus, sum(CAST(l_quantity AS DECIMAL(18,2))) AS units FROM orders JOIN lineitem ON o_orderkey = l_orderkey GROUP BY 1"),
    "rel_outer_join": (outer_join, "SELECT toxic, count(*) AS n FROM documents FULL JOIN labels USING (doc_id) GROUP BY 1"),
    "rel_semi_anti": (semi_anti, "SELECT CASE WHEN doc_id IN (SELECT doc_id FROM labels) THEN 'labelled' ELSE 'unlabelled' END AS kind, count(*) AS n FROM documents GROUP BY 1"),
    "rel_theta_join": (theta_join, "SELECT x.n_nationkey AS a, y.n_nationkey AS b FROM nation x JOIN nation y ON x.n_nationkey < y.n_nationkey AND x.n_regionkey = y.n_regionkey"),
    "rel_range_join": (range_join, "SELECT b.event_id AS purchase_id, count(*) AS n FROM events b JOIN events e ON b.event_type = 'purchase' AND b.user_id = e.user_id AND e.ts > b.ts AND e.ts < b.ts + INTERVAL 1 DAY GROUP BY 1"),
    "rel_asof_join": (asof_join, "SELECT event_id, before_id FROM (SELECT event_id, event_type, last_value(CASE WHEN event_type <> 'purchase' THEN event_id END IGNORE NULLS) OVER (PARTITION BY user_id ORDER BY ts, event_id ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING) AS before_id FROM events) WHERE event_type = 'purchase'"),
    "rel_lateral_topk": (lateral_topk, "SELECT c_custkey, o_orderkey, CAST(r AS INT) AS r FROM (SELECT c_custkey, o_orderkey, row_number() OVER (PARTITION BY o_custkey ORDER BY o_totalprice DESC, o_orderkey) AS r FROM customer JOIN orders ON c_custkey = o_custkey WHERE c_nationkey = 0) WHERE r <= 2"),
    "rel_aggregates": (filtered_aggregates, "SELECT l_returnflag, count(*) AS n, count(*) FILTER (l_discount > 0.05) AS n_rebate, count(DISTINCT l_suppkey) AS n_supp, sum(CAST(l_quantity AS DECIMAL(18,2))) AS units FROM lineitem GROUP BY 1"),
    "rel_cube": (cube, "SELECT l_returnflag, l_linestatus, count(*) AS n FROM lineitem GROUP BY CUBE (l_returnflag, l_linestatus)"),
    "rel_rollup": (rollup, "SELECT o_orderstatus, o_orderpriority, count(*) AS n FROM orders GROUP BY ROLLUP (o_orderstatus, o_orderpriority)"),
    "rel_windows": (windows, "SELECT event_id, CAST(row_number() OVER w AS INT) AS n, lag(event_id) OVER w AS prev_id, lead(event_id) OVER w AS next_id, CAST(ntile(4) OVER w AS INT) AS quarter FROM events WINDOW w AS (PARTITION BY user_id ORDER BY ts, event_id)"),
    "rel_set_operations": (set_operations, """WITH c AS (SELECT c_nationkey AS k FROM customer), s AS (SELECT s_nationkey AS k FROM supplier)
        SELECT 'union all' AS what, count(*) AS n FROM (SELECT * FROM c UNION ALL SELECT * FROM s) UNION ALL SELECT 'union', count(*) FROM (SELECT * FROM c UNION SELECT * FROM s)
        UNION ALL SELECT 'intersect', count(*) FROM (SELECT * FROM c INTERSECT SELECT * FROM s) UNION ALL SELECT 'except all', count(*) FROM (SELECT * FROM c EXCEPT ALL SELECT * FROM s)
        UNION ALL SELECT 'intersect all', count(*) FROM (SELECT * FROM c INTERSECT ALL SELECT * FROM s)"""),
    "rel_pivot": (pivot, "SELECT o_orderstatus, count(*) FILTER (o_orderpriority = '1-URGENT') AS urgent, count(*) FILTER (o_orderpriority = '2-HIGH') AS high FROM orders GROUP BY 1"),
    "rel_strings": (strings, "SELECT p_partkey, upper(p_name) AS up, CAST(length(p_name) AS INT) AS len, substr(p_name, 1, 4) AS head, md5(p_name) AS digest, CAST(levenshtein(p_name, p_brand) AS INT) AS lev FROM part"),
    "rel_dates": (dates, "SELECT CAST(year(o_orderdate) AS INT) AS y, CAST(quarter(o_orderdate) AS INT) AS q, count(*) AS n FROM orders GROUP BY 1, 2"),
    "rel_json": (json_fields, "SELECT CAST(json_extract_string(props, '$.k') AS INT) AS k, count(*) AS n FROM events GROUP BY 1"),
    "rel_html_titles": (html_titles, "SELECT page_id, regexp_extract(html, '<title>(.*?)</title>', 1) AS title FROM pages"),
    "rel_arrays": (arrays, "SELECT vec_id, CAST(len(embedding) AS INT) AS dim, CAST(len(list_filter(embedding, lambda x: x > 0)) AS INT) AS positive FROM embeddings"),
    "rel_top_rows": (top_rows, "SELECT o_orderkey FROM orders ORDER BY o_totalprice DESC, o_orderkey LIMIT 100"),
    "rel_hash_sample": (hash_sample, "SELECT o_orderkey FROM orders WHERE (('0x' || substr(md5('42|sample|' || o_orderkey), 1, 13))::BIGINT / 4503599627370496.0) < 0.1"),
    "rel_approximate": (approximate, "SELECT true AS distinct_ok, true AS sketch_ok, true AS median_ok, true AS quantiles_ok FROM (SELECT count(*) FROM lineitem)"),
    "rel_arrow_function": (arrow_function, "SELECT vec_id, round(sqrt(list_sum(list_transform(CAST(embedding AS DOUBLE[]), lambda x: x * x))), 4) AS size, true AS same FROM embeddings"),
    "rel_grouped_function": (grouped_function, "SELECT c_nationkey, round(max(c_acctbal) - min(c_acctbal), 2) AS spread FROM customer GROUP BY 1"),
    "rel_table_function": (table_function, "SELECT p_partkey, CAST(unnest(range(len(ws))) AS INT) AS pos, unnest(ws) AS word FROM (SELECT p_partkey, string_split(p_name, ' ') AS ws FROM part)"),
    "rel_tumbling": (tumbling, "SELECT CAST(floor(epoch(ts) / 3600) * 3600 AS BIGINT) AS start, event_type, count(*) AS n FROM events GROUP BY 1, 2"),
}
