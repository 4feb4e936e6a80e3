"""Base tables and the cutting of pairs with controlled properties."""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkgraph.functions.draws import u52
from linkgraph.sources.pairs import TablePair
from linkgraph.sources.shared import written


def _t(spark: SparkSession, sf_dir: str, name: str) -> DataFrame:
    return spark.read.parquet(f"{sf_dir}/{name}.parquet")


def base(spark: SparkSession, sf_dir: str, name: str) -> tuple[DataFrame, str]:
    """A base table and its business key column."""
    t = lambda n: _t(spark, sf_dir, n)
    lineitem = lambda: t("lineitem").withColumn("line_key", F.md5(F.to_json(F.struct("*"))))  # noqa: E731  whole rows are distinct
    if name == "BA":
        orders = t("orders").groupBy("o_custkey").agg(F.count(F.lit(1)).alias("n_orders"), F.round(F.sum("o_totalprice"), 2).alias("total_spent"), F.min("o_orderdate").alias("first_order"), F.max("o_orderdate").alias("last_order"), F.min("o_orderpriority").alias("top_priority"))
        df = t("customer").join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey")).join(orders, F.col("c_custkey") == F.col("o_custkey"), "left")
        return df.select("c_custkey", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment", "n_name", "r_name", "r_regionkey", "n_orders", "total_spent", "first_order", "last_order", "top_priority"), "c_custkey"
    if name == "BB":
        df = t("orders").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).join(t("nation"), F.col("c_nationkey") == F.col("n_nationkey")).join(t("region"), F.col("n_regionkey") == F.col("r_regionkey"))
        return df.select("o_orderkey", "o_custkey", "o_orderstatus", "o_totalprice", "o_orderdate", "o_orderpriority", "c_name", "c_nationkey", "c_acctbal", "c_mktsegment", "n_name", "r_regionkey", "r_name"), "o_orderkey"
    if name == "BC":
        return lineitem().join(t("part"), F.col("l_partkey") == F.col("p_partkey")).drop("p_partkey"), "line_key"
    if name == "BD":
        e = t("events")
        prop = F.from_json("props", "map<string,string>").getItem("k")
        return e.select("event_id", F.to_date("ts").cast("string").alias("ev_date"), F.hour("ts").alias("ev_hour"), F.minute("ts").alias("ev_minute"), F.dayofweek("ts").alias("ev_weekday"), "user_id", "event_type", "value", prop.alias("prop_k"), F.floor(F.col("value") / 10).alias("value_band"), (F.col("event_id") % 97).alias("user_event_no")), "event_id"
    if name == "BE":
        return t("documents").join(t("labels"), "doc_id", "left").withColumn("n_words", F.size(F.split("text", " "))), "doc_id"
    if name == "BG":
        lines = t("lineitem").groupBy("l_partkey").agg(F.count_distinct("l_orderkey").alias("n_orders"), F.sum("l_quantity").alias("quantity"), F.round(F.sum("l_extendedprice"), 2).alias("revenue"), F.min("l_shipdate").alias("first_ship"), F.max("l_shipdate").alias("last_ship"))
        return t("part").join(lines, F.col("p_partkey") == F.col("l_partkey"), "left").drop("l_partkey"), "p_partkey"
    if name == "BH":
        return lineitem().join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).drop("o_orderkey"), "line_key"
    if name == "BW":
        df = lineitem().join(t("orders"), F.col("l_orderkey") == F.col("o_orderkey")).drop("o_orderkey").join(t("customer"), F.col("o_custkey") == F.col("c_custkey")).drop("c_custkey")
        df = df.join(t("part"), F.col("l_partkey") == F.col("p_partkey")).drop("p_partkey").join(t("supplier"), F.col("l_suppkey") == F.col("s_suppkey")).drop("s_suppkey")
        return df, "line_key"
    raise ValueError(f"no such base: {name}")


#: Other names of columns, for the right side, and what both sides say about them.
FAR = {
    "c_name": ("client_title", "full name of the buyer", "how the client is called"),
    "c_nationkey": ("country_code", "numeric country of the buyer", "code of the home country"),
    "c_acctbal": ("balance_amt", "money on the account of the buyer", "current account money of the client"),
    "c_mktsegment": ("industry_segment", "market segment the buyer works in", "segment of business"),
    "n_name": ("country_name", "name of the nation", "name of the country"),
    "r_name": ("region_title", "name of the world region", "name of the region"),
    "r_regionkey": ("region_code", "number of the world region", "code of the region"),
    "n_orders": ("order_count", "number of orders", "how many orders there are"),
    "total_spent": ("spent_amount", "total value of all orders", "total amount of the orders"),
    "first_order": ("earliest_order", "date of the first order", "date of the earliest order"),
    "last_order": ("latest_order", "date of the last order", "date of the latest order"),
    "top_priority": ("priority_class", "highest priority of the orders", "priority of the orders"),
    "o_custkey": ("client_number", "number of the buyer", "number of the client"),
    "o_orderstatus": ("state_flag", "status of the order", "state of the order"),
    "o_totalprice": ("amount_due", "total value of the order", "full price of the order"),
    "o_orderdate": ("placed_on", "day the order was made", "day of the order"),
    "o_orderpriority": ("urgency", "priority of the order", "urgency of the order"),
    "p_name": ("item_label", "name of the product", "wording of the product"),
    "p_brand": ("maker_brand", "brand of the product", "brand of the item"),
    "p_type": ("item_kind", "type of the product", "kind of product"),
    "p_size": ("item_size", "size of the product", "size of the item"),
    "p_retailprice": ("list_price", "retail price of the product", "price on the list"),
    "l_orderkey": ("order_number", "number of the order", "number of the order of the line"),
    "l_partkey": ("item_number", "number of the product", "number of the item"),
    "l_suppkey": ("vendor_number", "number of the seller", "number of the vendor"),
    "l_linenumber": ("position", "line of the order", "position within the order"),
    "l_quantity": ("units", "quantity ordered", "number of units ordered"),
    "l_extendedprice": ("line_amount", "price of the line", "amount of the line"),
    "l_discount": ("rebate", "discount of the line", "rebate on the line"),
    "l_tax": ("duty", "tax of the line", "tax duty of the line"),
    "l_returnflag": ("returned", "whether the goods came back", "flag of returned goods"),
    "l_linestatus": ("line_state", "status of the line", "state of the line"),
    "l_shipdate": ("dispatched", "day the goods left", "shipping day of the goods"),
    "event_type": ("action", "kind of user event", "what the user did"),
    "user_id": ("member_number", "number of the user", "number of the member"),
    "value": ("measured", "value of the event", "measured value of the event"),
    "prop_k": ("property_k", "property of the event", "property k of the event"),
    "value_band": ("measured_band", "band of the value", "band of the measured value"),
    "ev_date": ("day", "date of the event", "day of the event"),
    "ev_hour": ("hour_of_day", "hour of the event", "hour of the day of the event"),
    "lang": ("language", "language of the text", "written language"),
    "source": ("origin", "source of the text", "origin of the text"),
    "n_chars": ("char_count", "number of characters", "count of characters"),
    "n_words": ("word_count", "number of words", "count of words"),
    "quality": ("quality_mark", "quality of the text", "mark of quality"),
    "toxic": ("toxic_mark", "whether the text is toxic", "mark of toxicity"),
    "quantity": ("units_sold", "quantity sold", "number of units sold"),
    "revenue": ("turnover", "revenue of the product", "turnover with the product"),
}

#: Near-unique columns, whose shared copies always differ on the right side.
PERTURBED = {"c_name", "c_acctbal", "o_totalprice", "l_extendedprice", "total_spent", "revenue"}


@dataclass(frozen=True)
class Cut:
    """How a pair is cut from a base."""

    name: str
    base: str
    shared: tuple[str, ...]
    left_only: tuple[str, ...]
    right_only: tuple[str, ...]
    rows: int
    shared_rows: int
    #: Share of missing cells on either side.
    missing: float = 0.1
    missing_right: float | None = None
    rename: str = "far"
    describe: bool = True
    #: scattered, unimportant, important or row_clusters
    pattern: str = "unimportant"
    seed: int = 42


def _perturbed(name: str, kind: str, c: Column, label: Column, seed: int) -> Column:
    """A variant of a shared value on the right side, drawn by row."""
    u = u52(seed, "variant", F.lit(name), label)
    if kind == "string":
        typo = F.concat(F.substring(c, 1, 3), F.expr(f"substring(`{name}`, 5)"))
        return F.when(u < 0.5, c).when(u < 0.8, F.upper(c)).otherwise(typo)
    return F.when(u < 0.7, c).otherwise(F.round(c, 0))


def _with_gaps(df: DataFrame, columns: list[str], key: str, side: int, cut: Cut) -> DataFrame:
    """Drops cells so that the wanted share is missing; natural gaps count."""
    rate = cut.missing if side == 0 or cut.missing_right is None else cut.missing_right
    if not rate:
        return df
    ids = {c for c in columns if "name" in c or c.endswith("key") or c in ("client_title", "client_number", "item_label", "order_number", "item_number")}
    weight = {c: 1.0 for c in columns}
    if cut.pattern == "unimportant":
        weight = {c: 0.3 if c in ids else 1.0 for c in columns}
    elif cut.pattern == "important":
        weight = {c: 1.0 if c in ids else 0.3 for c in columns}
    mean = sum(weight.values()) / len(columns)
    row_u = u52(cut.seed, f"row{side}", F.col(key))
    out = {}
    for c in columns:
        u = u52(cut.seed, f"gap{side}", F.lit(c), F.col(key))
        if cut.pattern == "row_clusters":
            gone = (row_u < rate * 2) & (u < 0.5)
        else:
            gone = u < min(0.95, rate * weight[c] / mean)
        out[c] = F.when(~gone, F.col(f"`{c}`"))
    return df.withColumns(out)


def cut_pair(spark: SparkSession, sf_dir: str, cut: Cut) -> TablePair:
    """Two tables from one base, with known column and record matches.

    Rows are the first by a draw from their key: shared ones, then each side's
    own.  The business key tells rows apart but is no data of either table.
    They are chosen once and written, as both sides and the matches read them.
    """
    df, key = base(spark, sf_dir, cut.base)
    columns = [*dict.fromkeys([*cut.shared, *cut.left_only, *cut.right_only])]
    own = cut.rows - cut.shared_rows
    chosen = df.select(F.col(key).cast("string").alias("row_key"), *columns).withColumn("_u", u52(cut.seed, "cut" + cut.base, F.col("row_key")))
    chosen = chosen.orderBy("_u", "row_key").limit(cut.shared_rows + 2 * own)
    # of the chosen rows only, whose number is a parameter
    numbered = chosen.withColumn("_n", F.row_number().over(Window.orderBy("_u", "row_key"))).drop("_u")
    chosen = written(numbered.repartition(spark.sparkContext.defaultParallelism, "row_key"))
    left_cols, right_cols = [*cut.shared, *cut.left_only], [*cut.shared, *cut.right_only]
    kinds = dict(df.dtypes)
    left = chosen.filter(F.col("_n") <= cut.rows).select("row_key", *left_cols)
    right = chosen.filter((F.col("_n") <= cut.shared_rows) | (F.col("_n") > cut.rows))
    variants = {c: _perturbed(c, kinds[c], F.col(c), F.col("row_key"), cut.seed) for c in cut.shared if c in PERTURBED}
    right = (right.withColumns(variants) if variants else right).select("row_key", *right_cols)
    if cut.rename == "far":
        new = {c: FAR.get(c, (f"{c}_2",))[0] for c in right_cols}
    elif cut.rename == "near":
        new = {c: "r_" + c.split("_", 1)[-1] for c in right_cols}
    elif cut.rename == "codes":
        new = {c: f"fld{k:02d}x" for k, c in enumerate(right_cols)}
    else:
        new = {c: c for c in right_cols}
    if cut.rename == "codes":
        left_new = {c: f"col_{k:03d}" for k, c in enumerate(left_cols)}
        left = left.withColumnsRenamed(left_new)
    else:
        left_new = {c: c for c in left_cols}
    right = right.withColumnsRenamed(new)
    left = _with_gaps(left, [left_new[c] for c in left_cols], "row_key", 0, cut)
    right = _with_gaps(right, [new[c] for c in right_cols], "row_key", 1, cut)
    descriptions = {}
    if cut.describe and cut.rename != "codes":
        descriptions = {(0, left_new[c]): FAR[c][1] for c in left_cols if c in FAR} | {(1, new[c]): FAR[c][2] for c in right_cols if c in FAR}
    shared_keys = chosen.filter(F.col("_n") <= cut.shared_rows).select(F.concat(F.lit("0:"), "row_key").alias("left_key"), F.concat(F.lit("1:"), "row_key").alias("right_key"))
    return TablePair((left, right), ("row_key", "row_key"), descriptions, tuple((left_new[c], new[c]) for c in cut.shared), shared_keys, (False, False), cut.name)
