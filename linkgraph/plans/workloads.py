"""The experiments' workloads: pairs cut from the given tables with stated properties."""

from __future__ import annotations

from dataclasses import replace

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.functions.draws import u52
from linkgraph.operators import properties
from linkgraph.operators.prepare import cells
from linkgraph.params import Params
from linkgraph.plans import link as plans
from linkgraph.sources.bases import Cut, cut_pair
from linkgraph.sources.pairs import TablePair

_BA = ("c_name", "c_acctbal", "c_mktsegment", "n_name", "total_spent"), ("c_nationkey", "n_orders", "first_order"), ("r_name", "last_order", "top_priority")
_BB3 = ("c_name", "o_totalprice", "o_orderdate"), ("o_custkey", "o_orderstatus", "c_mktsegment", "n_name", "c_nationkey"), ("o_orderpriority", "c_acctbal", "r_name", "r_regionkey", "o_orderkey")
_BB4 = ("c_name", "o_totalprice", "o_orderdate", "n_name"), ("o_custkey", "o_orderstatus", "c_mktsegment", "c_nationkey"), ("o_orderpriority", "c_acctbal", "r_name", "r_regionkey")
_BC7 = ("l_orderkey", "l_partkey", "l_extendedprice", "l_shipdate", "p_name", "l_quantity", "p_retailprice"), ("l_suppkey", "l_discount", "l_returnflag", "p_brand"), ("l_linenumber", "l_tax", "l_linestatus", "p_type")
_BC6 = ("l_orderkey", "l_partkey", "l_extendedprice", "l_shipdate", "p_name", "l_quantity"), ("l_suppkey", "l_discount", "l_returnflag", "p_brand"), ("l_linenumber", "l_tax", "l_linestatus", "p_type")
_BD = ("user_id", "ev_date", "value"), ("ev_hour", "event_type", "prop_k", "event_id"), ("ev_minute", "ev_weekday", "value_band", "user_event_no")
_BE = ("source", "n_chars", "lang", "n_words"), ("quality",), ("toxic",)
_BG = ("p_name", "p_brand", "p_retailprice", "quantity", "revenue"), ("p_type", "n_orders", "first_ship"), ("p_size", "last_ship", "p_partkey")
_BH = ("l_orderkey", "l_partkey", "l_extendedprice", "l_shipdate", "o_totalprice"), ("l_suppkey", "l_discount", "o_orderstatus"), ("l_tax", "o_custkey", "o_orderpriority")
_BW_OWN = ("l_linenumber", "l_discount", "l_returnflag", "o_orderstatus", "o_orderpriority", "p_brand", "p_type", "c_mktsegment", "s_acctbal"), ("l_tax", "l_linestatus", "l_shipdate", "p_size", "p_retailprice", "c_acctbal", "c_nationkey", "s_name", "s_nationkey")
_BW_SHARED = ("c_name", "l_extendedprice", "p_name", "o_totalprice", "l_orderkey")


def _cut(name: str, base: str, cols, rows: int, shared: int, missing: float, **more) -> Cut:
    return Cut(name, base, cols[0], cols[1], cols[2], rows, shared, missing, **more)


def _bw(name: str, n: int) -> Cut:
    left, right = _BW_OWN
    return Cut(name, "BW", _BW_SHARED[:n], left[: 10 - n], right[: 10 - n], 2000, 400, 0.10)


#: Pair by letter, with the sizes, overlaps and missing rates of the experiments.
CUTS = {
    "A": _cut("A", "BA", _BA, 777, 55, 0.0584),
    "B": _cut("B", "BB", (_BB3[0], _BB3[1], _BB3[2][:4] + ("o_orderstatus",)), 6453, 281, 0.0943),
    "C": _cut("C", "BC", _BC7, 4738, 305, 0.1060),
    "D": _cut("D", "BD", (_BD[0], _BD[1][:3], _BD[2]), 3853, 202, 0.1538),
    "E": _cut("E", "BE", _BE, 556, 114, 0.1964, describe=False),
    "F": _cut("F", "BA", _BA, 750, 150, 0.10),
    "G": _cut("G", "BG", (_BG[0], _BG[1], ("p_size", "last_ship", "n_orders")), 750, 150, 0.10),
    "H": _cut("H", "BH", _BH, 750, 150, 0.10, rename="codes", describe=False),
    "I": _cut("I", "BC", _BC6, 15000, 3000, 0.10),
    "J": _cut("J", "BC", _BC6, 2500, 500, 0.10),
    "K": _cut("K", "BC", _BC6, 250, 50, 0.10),
    "L": _bw("L", 1),
    "M": _bw("M", 3),
    "N": _bw("N", 5),
    "O": _cut("O", "BB", _BB4, 2000, 200, 0.10),
    "P": _cut("P", "BB", _BB4, 2000, 600, 0.10),
    "Q": _cut("Q", "BB", _BB4, 2000, 1000, 0.10),
}
#: Numeric columns alone; long texts and addresses, nearly all of them different.
MORE_CUTS = {
    "NUM": _cut("NUM", "BC", (("l_orderkey", "l_extendedprice", "l_quantity", "p_retailprice"), ("l_partkey", "l_discount"), ("l_suppkey", "l_tax")), 2000, 400, 0.10),
    "DIV": _cut("DIV", "BE", (("text", "n_chars", "source"), ("lang",), ("n_words",)), 400, 80, 0.05),
}
BLOCKS = {"F": "specificity", "G": "specificity", "H": "specificity", "I": "size", "J": "size", "K": "size", "L": "columns", "M": "columns", "N": "columns", "O": "rows", "P": "rows", "Q": "rows"}

#: Walk settings of the experiments, fixed on a pair outside of them; the same for both methods.
RUN = Params(walks_per_node=4, walk_length=12, dim=128, er_candidates="all")

#: Missing rates of either side in the sweep; where gaps lie, at two of the rates.
RATES = (0.0, 0.05, 0.1, 0.2, 0.3, 0.4, 0.5)
PATTERNS = ("unimportant", "important", "scattered", "row_clusters")


def scaled(cut: Cut, scale: float) -> Cut:
    return replace(cut, rows=max(40, int(cut.rows * scale)), shared_rows=max(10, int(cut.shared_rows * scale)))


def workload(spark: SparkSession, sf_dir: str, letter: str, scale: float = 1.0) -> TablePair:
    return cut_pair(spark, sf_dir, scaled(CUTS[letter], scale))


def achieved(spark: SparkSession, pair: TablePair) -> DataFrame:
    """Properties that a pair really has: cells, missing share, overlaps."""
    size = properties.data_size(pair).filter("what = 'pair'").select("cells")
    rate = properties.missing_rate(cells(pair)).filter("side = 'all'").select("rate")
    rows = properties.overlap_rows(pair).select(F.col("overlap").alias("row_overlap"))
    return size.crossJoin(rate).crossJoin(rows).select(F.lit(pair.name).alias("workload"), "cells", F.col("rate").alias("missing"), F.lit(round(properties.overlap_columns(pair), 6)).alias("column_overlap"), "row_overlap")  # one row each


def run(spark: SparkSession, sf_dir: str, letter: str, p: Params = RUN, scale: float = 1.0) -> DataFrame:
    return plans.experiment(spark, workload(spark, sf_dir, letter, scale), p)


def missing_sweep(spark: SparkSession, sf_dir: str, rates=RATES, rows: int = CUTS["A"].rows, shared: int = CUTS["A"].shared_rows, p: Params = RUN, patterns=("unimportant",)) -> DataFrame:
    """Scores over a grid of left and right missing rates, and of where gaps lie."""
    def run(pattern: str, a: float, b: float) -> list:
        cut = replace(_cut(f"MS-{a}-{b}", "BA", _BA, rows, shared, a), missing_right=b, pattern=pattern)
        got = plans.experiment(spark, cut_pair(spark, sf_dir, cut), p)
        return [(pattern, a, b, r["method"], r["task"], r["f1"]) for r in got.collect()]

    grid = [(pattern, a, b) for pattern in patterns for a in rates for b in rates]
    out = [r for part in plans.at_once([lambda c=c: run(*c) for c in grid]) for r in part]
    return spark.createDataFrame(out, "pattern string, left_rate double, right_rate double, method string, task string, f1 double")


def confusable(spark: SparkSession, sf_dir: str) -> TablePair:
    """Per-user extremes of events, where close names mean different things."""
    e = spark.read.parquet(f"{sf_dir}/events.parquet")
    per = e.groupBy("user_id").agg(F.min("value").alias("min_value"), F.max("value").alias("max_value"), F.min("ts").alias("first_ts"), F.max("ts").alias("last_ts"))
    left = per.filter("user_id % 4 <> 0")
    right = per.filter("user_id % 4 <> 1").withColumnsRenamed({"min_value": "value_min", "max_value": "value_max", "first_ts": "ts_first", "last_ts": "ts_last"})
    shared = per.filter("user_id % 4 > 1").select(F.concat(F.lit("0:"), "user_id").alias("left_key"), F.concat(F.lit("1:"), "user_id").alias("right_key"))
    true = (("min_value", "value_min"), ("max_value", "value_max"), ("first_ts", "ts_first"), ("last_ts", "ts_last"))
    return TablePair((left, right), ("user_id", "user_id"), {}, true, shared, (False, False), "LX")


def variants(spark: SparkSession, sf_dir: str) -> TablePair:
    """Parts and their names with a word cut short, two letters swapped, or the case changed."""
    part = spark.read.parquet(f"{sf_dir}/part.parquet").select("p_partkey", "p_name", "p_brand")
    u = u52(42, "variant", F.col("p_partkey"))
    first, last = F.split("p_name", " ")[0], F.element_at(F.split("p_name", " "), -1)
    swapped = F.concat(F.substring("p_name", 1, 2), F.substring("p_name", 4, 1), F.substring("p_name", 3, 1), F.expr("substring(p_name, 5)"))
    other = F.when(u < 0.3, F.concat_ws(" ", first, F.concat(F.substring(last, 1, 4), F.lit(".")))).when(u < 0.6, swapped).otherwise(F.upper("p_name"))
    left = part.filter("p_partkey % 4 <> 0").select("p_partkey", "p_name", "p_brand")
    right = part.filter("p_partkey % 4 <> 1").select("p_partkey", other.alias("item_label"), F.col("p_brand").alias("maker"))
    shared = part.filter("p_partkey % 4 > 1").select(F.concat(F.lit("0:"), F.col("p_partkey").cast("string")).alias("left_key"), F.concat(F.lit("1:"), F.col("p_partkey").cast("string")).alias("right_key"))
    return TablePair((left, right), ("p_partkey", "p_partkey"), {}, (("p_name", "item_label"), ("p_brand", "maker")), shared, (False, False), "TOK")


def copied_documents(spark: SparkSession, sf_dir: str) -> TablePair:
    """Documents of even and of odd number; equal texts are the same record."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text", "lang", "source")
    left, right = docs.filter("doc_id % 2 = 0"), docs.filter("doc_id % 2 = 1").withColumnsRenamed({"text": "body", "lang": "language", "source": "origin"})
    a, b = left.select(F.concat(F.lit("0:"), F.col("doc_id").cast("string")).alias("left_key"), F.sha2("text", 256).alias("h")), right.select(F.concat(F.lit("1:"), F.col("doc_id").cast("string")).alias("right_key"), F.sha2("body", 256).alias("h"))
    return TablePair((left, right), ("doc_id", "doc_id"), {}, (("text", "body"), ("lang", "language"), ("source", "origin")), a.join(b, "h").drop("h"), (False, False), "NAT2")


def held_passages(spark: SparkSession, sf_dir: str, table: str = "benchmark", width: int = 8) -> DataFrame:
    """Share of each item's (or turn's) windows of words that a document holds: semi-structured text matched by containment."""
    windows = lambda df, key: (
        df.select(F.col(key).alias(key), F.filter(F.split(F.lower("text"), r"[^\p{L}0-9]+"), lambda w: w != "").alias("ws"))
        .filter(F.size("ws") >= width)
        .select(key, F.explode(F.array_distinct(F.expr(f"transform(sequence(1, size(ws) - {width - 1}), i -> array_join(slice(ws, i, {width}), ' '))"))).alias("g"))
    )
    items = spark.read.parquet(f"{sf_dir}/{table}.parquet")
    items = items.select("item_id", "text") if table == "benchmark" else items.select(F.concat_ws(":", "conv_id", "turn").alias("item_id"), "text")
    mine, theirs = windows(items, "item_id"), windows(spark.read.parquet(f"{sf_dir}/documents.parquet"), "doc_id")
    total = mine.groupBy("item_id").agg(F.count(F.lit(1)).alias("n"))
    met = mine.join(theirs, "g").groupBy("item_id", "doc_id").agg(F.count(F.lit(1)).alias("hits"))
    return met.join(total, "item_id").select(F.col("item_id").cast("string").alias("item_id"), "doc_id", F.round(F.col("hits") / F.col("n"), 6).alias("held")).filter("held >= 0.5")


def _held_sql(table: str, key: str, width: int = 8) -> str:
    grams = lambda k, t: f"SELECT DISTINCT k, array_to_string(ws[i:i + {width - 1}], ' ') AS g FROM (SELECT k, ws, unnest(range(1, CAST(len(ws) AS BIGINT) - {width - 2})) AS i FROM (SELECT {k} AS k, list_filter(string_split_regex(lower(text), '[^\\p{{L}}0-9]+'), lambda w: w <> '') AS ws FROM {t}) WHERE len(ws) >= {width})"
    return f"WITH m AS ({grams(key, table)}), d AS ({grams('doc_id', 'documents')}), t AS (SELECT k, count(*) AS n FROM m GROUP BY 1), h AS (SELECT m.k AS item, d.k AS doc_id, count(*) AS hits FROM m JOIN d USING (g) GROUP BY 1, 2) SELECT CAST(item AS VARCHAR) AS item_id, doc_id, round(hits / n, 6) AS held FROM h JOIN t ON t.k = item WHERE round(hits / n, 6) >= 0.5"


def experiment_one(spark: SparkSession, sf_dir: str, p: Params = RUN, scale: float = 1.0) -> DataFrame:
    """Five bases, both graph methods, both tasks."""
    out = None
    for letter in "ABCDE":
        part = run(spark, sf_dir, letter, p, scale)
        out = part if out is None else out.union(part)
    return out


def experiment_two(spark: SparkSession, sf_dir: str, p: Params = RUN, scale: float = 1.0) -> DataFrame:
    """One property at a time: specificity, size, column overlap, row overlap."""
    out = None
    for letter, block in BLOCKS.items():
        part = run(spark, sf_dir, letter, p, scale).withColumn("block", F.lit(block))
        out = part if out is None else out.union(part)
    return out


def _wl(letter: str):
    return lambda spark, sf_dir: run(spark, sf_dir, letter)


def _props(letter: str):
    return lambda spark, sf_dir: achieved(spark, workload(spark, sf_dir, letter))


#: All at the size and with the walks of the experiments; tests run smaller ones through ``run``.
QUERIES = {f"wl_{k}": (_wl(k), None) for k in CUTS} | {f"wl_{k}_properties": (_props(k), None) for k in CUTS}
QUERIES |= {f"wl_{k}": (lambda s, d, c=c: plans.experiment(s, cut_pair(s, d, c), RUN), None) for k, c in MORE_CUTS.items()}
QUERIES["wl_TOK"] = (lambda s, d: plans.experiment(s, variants(s, d), replace(RUN, token_mode="cell")), None)
QUERIES["wl_NAT2"] = (lambda s, d: plans.experiment(s, copied_documents(s, d), RUN), None)
QUERIES["wl_NAT3"] = (lambda s, d: held_passages(s, d), _held_sql("benchmark", "item_id"))
QUERIES["wl_NAT3_turns"] = (lambda s, d: held_passages(s, d, "conversations"), _held_sql("conversations", "conv_id || ':' || turn"))
QUERIES["wl_seeds"] = (lambda s, d: plans.repeat(s, workload(s, d, "K"), p=RUN), None)
QUERIES["wl_confusable"] = (lambda s, d: plans.experiment(s, confusable(s, d), RUN), None)
QUERIES["wl_missing_sweep"] = (lambda s, d: missing_sweep(s, d), None)
QUERIES["wl_missing_patterns"] = (lambda s, d: missing_sweep(s, d, (0.2, 0.4), patterns=PATTERNS), None)
QUERIES["wl_ablation"] = (lambda s, d: plans.ablate(s, workload(s, d, "A"), RUN), None)
