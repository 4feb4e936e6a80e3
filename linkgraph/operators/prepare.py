"""From tables to cells and tokens."""

from __future__ import annotations

from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F
from pyspark.sql import types as T

from linkgraph.sources.pairs import TablePair

PLACEHOLDERS = ("", "na", "n/a", "null", "none", "nan")
_NUMERIC = (T.ByteType, T.ShortType, T.IntegerType, T.LongType, T.FloatType, T.DoubleType, T.DecimalType)
_FRACTION = (T.FloatType, T.DoubleType, T.DecimalType)


def normalize_missing(df: DataFrame, tokens: tuple[str, ...] = PLACEHOLDERS, zero_is_missing: tuple[str, ...] = ()) -> DataFrame:
    """Placeholders become nulls; zeros too in the columns named."""

    def clean(f: T.StructField) -> Column:
        c = F.col(f"`{f.name}`")
        bad = F.lit(False)
        if isinstance(f.dataType, T.StringType):
            bad = F.lower(F.trim(c)).isin(*tokens)
        elif isinstance(f.dataType, (T.FloatType, T.DoubleType)):
            bad = F.isnan(c)
        if f.name in zero_is_missing:
            bad = bad | (c.cast("double") == 0)
        return F.when(~F.coalesce(bad, F.lit(False)), c).alias(f.name)

    return df.select(*map(clean, df.schema.fields))


def blank_as_negative(df: DataFrame, cols: tuple[str, ...]) -> DataFrame:
    """In columns whose blanks mean "no", blanks become ``0``."""
    blank = lambda c: F.when(F.col(c).isNull() | (F.trim(F.col(c).cast("string")) == ""), F.lit("0")).otherwise(F.col(c).cast("string"))
    return df.withColumns({c: blank(c) for c in cols})


def drop_not_applicable(cells: DataFrame, rules: dict[str, str]) -> DataFrame:
    """Removes cells that a rule of their column marks as not applicable."""
    bad = F.lit(False)
    for cid, rule in rules.items():
        bad = bad | ((F.col("cid") == cid) & F.coalesce(F.expr(rule), F.lit(False)))
    return cells.filter(~bad)


def klass_of(field: T.StructField) -> str:
    return "numeric" if isinstance(field.dataType, _NUMERIC) else "character"


def infer_classes(df: DataFrame, share: float = 0.95) -> DataFrame:
    """(attr, klass): strings count as numeric if enough of their values parse."""
    parsed = {f.name: F.avg(F.when(F.col(f"`{f.name}`").isNotNull(), F.expr(f"try_cast(`{f.name}` as double) is not null").cast("double"))) for f in df.schema.fields if isinstance(f.dataType, T.StringType)}
    fixed = {f.name: F.lit(1.0 if klass_of(f) == "numeric" else 0.0) for f in df.schema.fields if f.name not in parsed}
    row = df.agg(*[(parsed | fixed)[c].alias(c) for c in df.columns]) if parsed else df.limit(1).agg(*[F.max(fixed[c]).alias(c) for c in df.columns])
    stacked = row.select(F.explode(F.array(*[F.struct(F.lit(c).alias("attr"), F.coalesce(F.col(f"`{c}`"), F.lit(0.0)).alias("p")) for c in df.columns])).alias("x"))
    return stacked.select("x.attr", F.when(F.col("x.p") >= share, "numeric").otherwise("character").alias("klass"))


def canonical(field: T.StructField) -> Column:
    """A value as text: strings trimmed and lower, fractions without trailing zeros.

    A fraction that four decimals do not give back whole keeps its shortest text,
    so that no two values share one.
    """
    c = F.col(f"`{field.name}`")
    if isinstance(field.dataType, _FRACTION):
        short = c.try_cast("decimal(38,4)")
        plain = F.regexp_replace(short.cast("string"), r"\.?0+$", "")
        return F.when(short.cast(field.dataType) == c, plain).otherwise(F.lower(c.cast("string")))
    if isinstance(field.dataType, T.StringType):
        return F.lower(F.trim(F.regexp_replace(c, r"\s+", " ")))
    if isinstance(field.dataType, (T.ArrayType, T.MapType, T.StructType)):
        return F.to_json(c)
    return c.cast("string")


def with_rid(df: DataFrame, side: int, key: str | None = None) -> DataFrame:
    """Adds a row id: from the key, or from the whole row and its occurrence number."""
    if key is not None:
        return df.withColumn("rid", F.concat(F.lit(f"{side}:"), F.col(f"`{key}`").cast("string")))
    whole = F.md5(F.to_json(F.struct(*[F.col(f"`{c}`") for c in df.columns])))
    numbered = df.withColumn("_h", whole)
    w = Window.partitionBy("_h").orderBy("_h")
    return numbered.withColumn("rid", F.concat(F.lit(f"{side}:"), "_h", F.lit("#"), F.row_number().over(w).cast("string"))).drop("_h")


def melt(df: DataFrame, side: int, rid: Column, columns: list[str]) -> DataFrame:
    """One row per cell: (side, rid, cid, pos, val, is_missing); one scan, no shuffle."""
    fields = {f.name: f for f in df.schema.fields}
    wide = df.select(F.concat(F.lit(f"{side}:"), rid.cast("string")).alias("rid"), *[canonical(fields[c]).alias(c) for c in columns])
    long = wide.unpivot(["rid"], columns, "attr", "val")
    pos = F.element_at(F.create_map(*[x for k, c in enumerate(columns) for x in (F.lit(c), F.lit(k))]), F.col("attr"))
    value = F.when(~F.col("val").isin(*PLACEHOLDERS), F.col("val"))
    return long.select(F.lit(side).alias("side"), "rid", F.concat(F.lit(f"{side}:"), "attr").alias("cid"), pos.alias("pos"), value.alias("val"), value.isNull().alias("is_missing"))


def cells(pair: TablePair) -> DataFrame:
    out = None
    for side, table in enumerate(pair.tables):
        part = melt(table, side, F.col(f"`{pair.keys[side]}`"), pair.columns(side))
        out = part if out is None else out.union(part)
    return out


def tokenize(cell_rows: DataFrame, mode: str = "token") -> DataFrame:
    """(rid, cid, tok, occ): the tokens of each cell, or its whole value."""
    seen = cell_rows.filter("not is_missing")
    if mode == "cell":
        return seen.select("rid", "cid", F.col("val").alias("tok"), F.lit(1).cast("long").alias("occ"))
    words = F.filter(F.split("val", r"[^\p{L}0-9.:-]+"), lambda w: w.rlike(r"[\p{L}0-9]"))
    return seen.select("rid", "cid", F.explode(words).alias("tok")).groupBy("rid", "cid", "tok").agg(F.count(F.lit(1)).alias("occ"))


def sentence(name: str, description: str | None, phrase: str = "meaning") -> str:
    """Metadata sentence of a column: its name, explained by its description."""
    import re

    words = re.sub(r"([a-z0-9])([A-Z])", r"\1 \2", name.replace("_", " ")).strip().lower()
    return f"{words} {phrase} {description.lower()}" if description else words
