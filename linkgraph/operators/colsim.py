"""Similarity of columns: metadata, value statistics, and their adaptive blend."""

from __future__ import annotations

from collections.abc import Callable

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.functions.similarity import gap, name_similarity, unit_cosine
from linkgraph.operators.prepare import PLACEHOLDERS, canonical, cells, klass_of, sentence
from linkgraph.params import Params
from linkgraph.sources.pairs import TablePair

NUMERIC_SLOTS = ("mean", "low", "high", "var", "sd")
CHAR_SLOTS = ("r_space", "r_punct", "r_special", "r_digit")


def hashed_encode(texts: DataFrame, key: str, text: str, dim: int = 64, nmin: int = 3, nmax: int = 4) -> DataFrame:
    """(key, vec): signed hashing of words and character n-grams, without a trained model.

    Bucket and sign of a feature come from its digest, so any engine agrees.
    """
    padded = F.concat(F.lit("<"), F.col("w"), F.lit(">"))
    words = texts.select(key, F.explode(F.filter(F.split(F.lower(F.col(text)), r"[^\p{L}0-9]+"), lambda w: w != "")).alias("w"))

    def of_length(n: int) -> Column:
        return F.transform(F.sequence(F.lit(1), F.greatest(F.length(padded) - n + 1, F.lit(1))), lambda i: F.substring(padded, i, n))

    grams = [of_length(n) for n in range(nmin, nmax + 1)]
    feats = words.select(key, F.explode(F.concat(F.array(F.concat(F.lit("="), "w")), *grams)).alias("f"))
    digest = F.md5("f")
    bucket = F.conv(F.substring(digest, 1, 8), 16, 10).cast("long") % dim
    sign = F.when(F.conv(F.substring(digest, 9, 1), 16, 10).cast("int") % 2 == 0, 1).otherwise(-1)
    slots = feats.groupBy(key, bucket.alias("b")).agg(F.sum(sign).cast("double").alias("x"))
    by = slots.groupBy(key).agg(F.map_from_entries(F.collect_list(F.struct("b", "x"))).alias("m"))
    vec = F.transform(F.sequence(F.lit(0).cast("long"), F.lit(dim - 1).cast("long")), lambda i: F.coalesce(F.element_at("m", i), F.lit(0.0)))
    return by.select(key, vec.alias("vec"))


def lookup_encode(texts: DataFrame, key: str, text: str, table: DataFrame, dim: int = 64) -> DataFrame:
    """Vectors from a given (text, vec) table, hashed n-grams for texts it lacks."""
    hashed = hashed_encode(texts, key, text, dim).withColumnRenamed("vec", "_h")
    found = texts.join(table.select(F.col("text").alias(text), F.col("vec").alias("_t")), text, "left")
    return found.join(hashed, key, "left").select(key, F.coalesce("_t", "_h").alias("vec"))


def metadata(spark: SparkSession, pair: TablePair) -> DataFrame:
    """(side, cid, name, sentence) of every column."""
    rows = [(s, f"{s}:{c}", c, sentence(c, pair.descriptions.get((s, c)))) for s in range(len(pair.tables)) for c in pair.columns(s)]
    return spark.createDataFrame(rows, "side int, cid string, name string, sentence string")


def scanned_metadata(spark: SparkSession, pair: TablePair) -> DataFrame:
    """``metadata`` of the columns that a scan of the tables finds, beside their filled cells ``n_filled``.

    One aggregate a table; columns without a value and tables without rows stay.
    """
    out = None
    for side, table in enumerate(pair.tables):
        filled = table.agg(*[F.count(f"`{c}`").alias(c) for c in pair.columns(side)]).unpivot([], pair.columns(side), "name", "n_filled")
        part = filled.select(F.lit(side).alias("side"), F.concat(F.lit(f"{side}:"), "name").alias("cid"), "name", "n_filled")
        out = part if out is None else out.union(part)
    told = metadata(spark, pair).select("cid", "sentence")
    # true of every count; it keeps the counts, and so the scan, in plans that show names alone
    return out.join(F.broadcast(told), "cid").filter("n_filled >= 0").select("side", "cid", "name", "sentence", "n_filled")


def profile(pair: TablePair) -> DataFrame:
    """Statistics of every column, one pass over each table and one over its cells.

    (cid, klass, n_rows, n_valid, n_distinct, numeric and character features,
    s_ling); features of the other class are null.
    """
    out = None
    for side, table in enumerate(pair.tables):
        fields = {f.name: f for f in table.schema.fields}
        columns = pair.columns(side)
        aggs: list[Column] = [F.count(F.lit(1)).alias("n")]
        for k, c in enumerate(columns):
            text = canonical(fields[c])
            text = F.when(~text.isin(*PLACEHOLDERS), text)
            number = F.when(text.isNotNull(), F.col(f"`{c}`").cast("double")) if klass_of(fields[c]) == "numeric" else F.lit(None).cast("double")
            share = lambda pattern, text=text: F.avg((F.length(text) - F.length(F.regexp_replace(text, pattern, ""))) / F.length(text))
            aggs.append(F.count(text).alias(f"v{k}"))
            aggs += [f(number).alias(f"{slot}{k}") for slot, f in zip(NUMERIC_SLOTS, (F.avg, F.min, F.max, F.var_pop, F.stddev_pop), strict=True)]
            aggs += [share(p).alias(f"{slot}{k}") for slot, p in zip(CHAR_SLOTS, (r"\s", r"[!-/:-@\[-`{-~]", r"[^\p{L}0-9\s!-/:-@\[-`{-~]", "[0-9]"), strict=True)]
            aggs.append(F.avg(text.rlike(r"\p{L}").cast("double")).alias(f"ling{k}"))
        row = table.agg(*aggs)
        structs = []
        for k, c in enumerate(columns):
            klass = klass_of(fields[c])
            use = lambda slot, want, k=k, klass=klass: (F.col(f"{slot}{k}") if klass == want else F.lit(None).cast("double")).alias(slot)
            structs.append(
                F.struct(
                    F.lit(f"{side}:{c}").alias("cid"), F.lit(side).alias("side"), F.lit(c).alias("name"), F.lit(klass).alias("klass"), F.col("n").alias("n_rows"), F.col(f"v{k}").alias("n_valid"),
                    *[use(s, "numeric") for s in NUMERIC_SLOTS], *[use(s, "character") for s in CHAR_SLOTS],
                    F.coalesce(F.col(f"ling{k}"), F.lit(0.0)).alias("s_ling"),
                )
            )
        part = row.select(F.inline(F.array(*structs)))
        out = part if out is None else out.union(part)
    # distinct values from the long form: one shuffle of values combined map-side,
    # where several distinct counts in one aggregate would copy every row per column
    distinct = cells(pair).filter("not is_missing").groupBy("cid").agg(F.count_distinct("val").alias("n_distinct"))
    return out.join(F.broadcast(distinct), "cid", "left").withColumn("n_distinct", F.coalesce("n_distinct", F.lit(0)))


def instance_vector(prof: DataFrame, scale: str = "raw") -> DataFrame:
    """Adds ``vec`` of nine slots, -1 where a feature does not apply, and the ``mask``."""
    slots = [F.col(s) for s in (*NUMERIC_SLOTS, *CHAR_SLOTS)]
    if scale == "signed_log":
        slots = [F.signum(s) * F.log1p(F.abs(s)) for s in slots]
    return prof.withColumns({"vec": F.array(*[F.coalesce(s, F.lit(-1.0)) for s in slots]), "mask": F.array(*[s.isNotNull() for s in slots])})


def gap_similarity(vi: Column, mi: Column, vj: Column, mj: Column, p: Params) -> Column:
    """One minus the mean relative gap over the slots that both columns have; 0 without any."""
    both = F.zip_with(mi, mj, lambda a, b: a & b)
    gaps = F.zip_with(F.zip_with(vi, vj, lambda a, b: gap(a, b, p.beta, p.eps, p.gap_denominator, p.gap_form)), both, lambda d, ok: F.when(ok, d))
    have = F.filter(gaps, lambda d: d.isNotNull())
    mean = F.aggregate(have, F.lit(0.0), lambda s, d: s + d) / F.size(have)
    closed = 1.0 - F.least(F.lit(1.0), mean)
    if p.gap_denominator == "abs":
        closed = F.greatest(F.lit(0.0), F.least(F.lit(1.0), closed))
    return F.when(F.size(have) > 0, closed).otherwise(F.lit(0.0))


def instance_cosine(vi: Column, mi: Column, vj: Column, mj: Column, cos_on: str) -> Column:
    if cos_on == "padded":
        return unit_cosine(vi, vj)
    both = F.zip_with(mi, mj, lambda a, b: a & b)
    only = lambda v: F.zip_with(v, both, lambda x, ok: F.when(ok, x).otherwise(F.lit(0.0)))
    return unit_cosine(only(vi), only(vj))


def confidence(n_valid: Column, n_rows: Column, n0: float) -> Column:
    """Evidence of one column: more rows and fewer gaps give more."""
    return n_valid / (n_valid + n0) * F.when(n_rows > 0, n_valid / n_rows).otherwise(0.0)


def column_similarity(spark: SparkSession, pair: TablePair, p: Params = Params(), prof: DataFrame | None = None, encoder: Callable[[DataFrame, str, str], DataFrame] | None = None) -> DataFrame:
    """All pairs of columns of different tables, every component kept.

    Columns are few; the pairs are a broadcast join of their one-row profiles.
    """
    prof = profile(pair) if prof is None else prof
    meta = metadata(spark, pair)
    vectors = (encoder or hashed_encode)(meta, "cid", "sentence").withColumnRenamed("vec", "s_vec")
    every = instance_vector(prof, p.feature_scale).join(F.broadcast(vectors), "cid", "left").withColumn("s_vec", F.coalesce("s_vec", F.array(F.lit(0.0))))
    left = every.select(*[F.col(c).alias(f"l_{c}") for c in every.columns])
    right = every.select(*[F.col(c).alias(f"r_{c}") for c in every.columns])
    both = left.join(F.broadcast(right), F.col("l_side") < F.col("r_side"))
    c = lambda n: F.col(n)
    both = both.withColumns({
        "s_cos": unit_cosine(c("l_s_vec"), c("r_s_vec")),
        "s_lev": name_similarity(c("l_name"), c("r_name")),
        "v_cos": instance_cosine(c("l_vec"), c("l_mask"), c("r_vec"), c("r_mask"), p.cos_on),
        "s_diff": gap_similarity(c("l_vec"), c("l_mask"), c("r_vec"), c("r_mask"), p),
        "r_value": F.least(confidence(c("l_n_valid"), c("l_n_rows"), p.n0), confidence(c("r_n_valid"), c("r_n_rows"), p.n0)),
    })
    alpha = F.lit(p.fixed_alpha) if p.fixed_alpha is not None else p.alpha_max - (p.alpha_max - p.alpha_min) * c("r_value")
    both = both.withColumns({"s_schema": (c("s_cos") + c("s_lev")) / 2, "s_instance": (c("v_cos") + c("s_diff")) / 2, "alpha": alpha})
    total = c("alpha") * c("s_schema") + (1 - c("alpha")) * c("s_instance")
    kept = total >= p.tau_cid if p.edge_cmp == "ge" else total > p.tau_cid
    return both.select(c("l_cid").alias("left_cid"), c("r_cid").alias("right_cid"), "s_cos", "s_lev", "s_schema", "v_cos", "s_diff", "s_instance", "r_value", "alpha", total.alias("s_total"), kept.alias("kept"))


def cid_edges(sim: DataFrame) -> DataFrame:
    return sim.filter("kept").select("left_cid", "right_cid", F.col("s_total").alias("weight"))


def candidate_columns(spark: SparkSession, pairs_meta: DataFrame, n: int = 3, least: int = 2) -> DataFrame:
    """Column pairs that share enough character n-grams of their names, for very many columns.

    An equi-join on n-grams instead of all pairs; n-grams of nearly all names do
    not propose pairs.
    """
    grams = pairs_meta.select("side", "cid", F.explode(F.array_distinct(F.transform(F.sequence(F.lit(1), F.greatest(F.length("name") - n + 1, F.lit(1))), lambda i: F.substring("name", i, n)))).alias("g"))
    a, b = grams.alias("a"), grams.alias("b")
    return a.join(b, (F.col("a.g") == F.col("b.g")) & (F.col("a.side") < F.col("b.side"))).groupBy(F.col("a.cid").alias("left_cid"), F.col("b.cid").alias("right_cid")).agg(F.count(F.lit(1)).alias("shared")).filter(F.col("shared") >= least)


