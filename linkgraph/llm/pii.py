"""Personal data in whole texts, on DataFrame and SQL functions alone.

The base kinds are regular expressions in forms that never recurse and never
scan a run of characters twice.  Their places come from the pieces between the
matches, so that no text is cut up row by row outside the JVM.

Contextual extraction then grows from seeds: the base kinds, and tokens whose
form alone marks a key (long hexadecimal strings, UUIDs).  Tokens that look like
identifiers and their left contexts form a weighted graph of patterns and
instances over the whole corpus; patterns are scored by the instances they
hold, instances by the patterns that hold them, for a few rounds; instances
that confident patterns vouch for are added: as kind ``secret`` where their form
marks a key, else as kind ``other``.  A form alone adds nothing.
"""

from __future__ import annotations

from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import materialise

KINDS = ("email", "ip", "card", "phone")

# Possessive forms of the stated patterns.  A match can start inside a run of
# its first class only where the run or the previous match begins.
_PATTERN = {
    "email": r"(?:\G|(?<![A-Za-z0-9._%+-]))[A-Za-z0-9._%+-]++@[A-Za-z0-9-]++(?:\.[A-Za-z0-9-]++)++",
    "ip": r"(?<![0-9])[0-9]++\.[0-9]++\.[0-9]++\.[0-9]++",
    "card": r"[0-9]++(?:[\x20-][0-9]++)*+",
    "phone": r"\+[0-9][\x20().0-9-]+[0-9]",
}
#: What a text must hold for the pattern to be tried at all.
_GATE = {"email": "contains(text, '@')", "ip": r"text rlike '[0-9]\\.[0-9]'", "card": "text rlike '[0-9]'", "phone": r"text rlike '\\+[0-9]'"}
_BYTE = "0*(?:25[0-5]|2[0-4][0-9]|1[0-9][0-9]|[0-9]{1,2})"
_VALID = {
    "email": "true",
    "ip": f"m rlike '^{_BYTE}(?:[.]{_BYTE}){{3}}$'",
    "card": "length(regexp_replace(m, '[^0-9]', '')) between 16 and 19 and luhn_check(regexp_replace(m, '[^0-9]', ''))",
    "phone": "length(regexp_replace(m, '[^0-9]', '')) between 8 and 15",
}
#: A token with a digit, of six characters at least; and up to two words that end a text.
_CANDIDATE = r"(?<![^\s])(?=[^\s0-9]*+[0-9])[^\s]{6,}+"
_CONTEXT = r"(?<![^\s])(?:[^\s]++[\x20\t]++){0,2}\z"
#: Forms that mark a key: 32 hexadecimal digits or more, or a UUID.
_KEY_FORM = "^(?:[0-9A-Fa-f]{32,}+|[0-9A-Fa-f]{8}-(?:[0-9A-Fa-f]{4}-){3}[0-9A-Fa-f]{12})$"
_SPAN = "struct<kind:string,s:int,e:int,bs:int,be:int>"
_NO_SPANS = f"cast(array() as array<{_SPAN}>)"


@dataclass(frozen=True)
class PiiParams:
    rounds: int = 3
    #: Least confidence of a pattern that vouches, and of an instance that is added.
    pattern_least: float = 0.5
    instance_least: float = 0.5
    #: Distinct seed instances that a vouching pattern must hold.
    seeds_least: int = 3
    #: Damping of a pattern's share, so that small patterns score low.
    damping: float = 1.0


def _let(name: str, value: str, body: str) -> str:
    """SQL for ``body`` with a name for a value that is computed once, not once an element of the lists in it."""
    return f"transform(array({value}), {name} -> {body})[0]"


#: Hits whose lengths are added up at a time.
_BLOCK = 256


def _ends(hits: str, pieces: str, length: str) -> str:
    """SQL for the running sums of the lengths of pieces and hits, in blocks, so that long lists cost little more a hit."""
    each = f"transform({hits}, (h, i) -> {length}({pieces}[i]) + {length}(h))"
    total = lambda x: f"aggregate({x}, 0, (t, v) -> t + v)"
    blocks = f"transform(sequence(0, (size(each) - 1) div {_BLOCK}), b -> {total(f'slice(each, b * {_BLOCK} + 1, {_BLOCK})')})"
    before = f"aggregate({blocks}, array(0), (t, v) -> array_append(t, element_at(t, -1) + v))"
    inside = total(f"slice(each, (i div {_BLOCK}) * {_BLOCK} + 1, i % {_BLOCK} + 1)")
    running = f"transform(each, (v, i) -> before[i div {_BLOCK}] + {inside})"
    return _let("each", each, _let("before", before, running))


def _placed(hits: str, pieces: str, item: str) -> Column:
    """Structs made by ``item`` from ``out``: each hit ``m``, its start ``s`` and end ``e`` in code points, ``bs`` and ``be`` in bytes."""
    ends = f"zip_with({_ends(hits, pieces, 'length')}, {_ends(hits, pieces, 'octet_length')}, (e, be) -> named_struct('e', e, 'be', be))"
    hit = f"zip_with({hits}, {ends}, (m, x) -> named_struct('m', m, 's', x.e - length(m), 'e', x.e, 'bs', x.be - octet_length(m), 'be', x.be))"
    return F.expr(_let("out", hit, item))


def base_spans(docs: DataFrame) -> DataFrame:
    """``docs`` with ``base``: spans of the base kinds, by kind, then start.

    A null text counts as empty.  Expects a column ``text``; keeps the others.
    """
    out = docs.withColumn("text", F.coalesce("text", F.lit("")))
    literal = lambda p: "r'" + p + "'"
    for kind in KINDS:
        out = out.withColumn(f"_{kind}_hits", F.expr(f"if({_GATE[kind]}, regexp_extract_all(text, {literal(_PATTERN[kind])}, 0), cast(array() as array<string>))"))
    for kind in KINDS:
        out = out.withColumn(f"_{kind}_pieces", F.expr(f"if(size(_{kind}_hits) > 0, split(text, {literal(_PATTERN[kind])}, -1), cast(array() as array<string>))"))
    for kind in KINDS:
        good = _VALID[kind].replace("m ", "x.m ").replace("(m,", "(x.m,")
        item = f"transform(filter(out, x -> {good}), x -> named_struct('kind', '{kind}', 's', x.s, 'e', x.e, 'bs', x.bs, 'be', x.be))"
        out = out.withColumn(f"_{kind}", F.when(F.expr(f"size(_{kind}_hits) = 0"), F.expr(_NO_SPANS)).otherwise(_placed(f"_{kind}_hits", f"_{kind}_pieces", item)))
    out = out.withColumn("base", F.concat(*[F.col(f"_{kind}") for kind in KINDS]))
    return out.drop(*[c for c in out.columns if c.startswith("_")])


def _candidates(spanned: DataFrame) -> DataFrame:
    """Adds ``cands``: identifier-like tokens with place, left context and whether a seed.

    The pattern takes the token alone; its context is read off what lies before
    it, which may hold other tokens.
    """
    literal = "r'" + _CANDIDATE + "'"
    out = spanned.withColumn("_hits", F.expr(f"if(text rlike '[0-9]', regexp_extract_all(text, {literal}, 0), cast(array() as array<string>))"))
    out = out.withColumn("_pieces", F.expr(f"if(size(_hits) > 0, split(text, {literal}, -1), cast(array() as array<string>))"))
    head, tail = r"r'^[^\p{L}\p{N}+]+'", r"r'[^\p{L}\p{N}]+$'"
    before = "concat(if(i > 1, _hits[i - 2], ''), if(i > 0, concat(_pieces[i - 1], _hits[i - 1]), ''), _pieces[i])"
    item = f"""transform(out, (x, i) -> named_struct(
        's', x.s + length(x.m) - length(regexp_replace(x.m, {head}, '')),
        'bs', x.bs + octet_length(x.m) - octet_length(regexp_replace(x.m, {head}, '')),
        'inst', regexp_replace(regexp_replace(x.m, {head}, ''), {tail}, ''),
        'left', lower(trim(regexp_extract({before}, r'{_CONTEXT}', 0)))))"""
    none = "cast(array() as array<struct<s:int,bs:int,inst:string,left:string>>)"
    out = out.withColumn("_placed", F.when(F.expr("size(_hits) = 0"), F.expr(none)).otherwise(_placed("_hits", "_pieces", item)))
    # base spans in as many stretches of the text as the root of their number, to look overlaps up in
    grid = "transform(sequence(0, n div wide), b -> filter(base, x -> x.s < (b + 1) * wide and x.e > b * wide))"
    met = "exists(sequence(x.s div wide, (x.s + length(x.inst) - 1) div wide), k -> exists(grid[k], b -> b.s < x.s + length(x.inst) and b.e > x.s))"
    made = f"""transform(filter(_placed, x -> length(x.inst) >= 6 and x.inst rlike '[0-9]'), x -> named_struct(
        's', x.s, 'e', x.s + length(x.inst), 'bs', x.bs, 'be', x.bs + octet_length(x.inst), 'left', x.left, 'inst', x.inst,
        'base', size(base) > 0 and {met},
        'key', x.inst rlike '{_KEY_FORM}'))"""
    cands = _let("n", "length(text)", _let("wide", "n div cast(ceil(sqrt(size(base) + 1)) as int) + 1", _let("grid", grid, made)))
    return out.withColumn("cands", F.expr(cands)).drop("_hits", "_pieces", "_placed")


def _edges(rows: DataFrame) -> DataFrame:
    """Pattern-instance edges of the corpus: ``(pattern, inst, seed, base)``."""
    shape = "regexp_replace(regexp_replace(c.inst, r'[0-9]+', '9'), r'[A-Za-z]+', 'a')"
    one = rows.select(F.explode("cands").alias("c"))
    patterns = f"filter(array(if(c.left = '', null, concat('2|', c.left)), if(c.left = '', null, concat('1|', regexp_extract(c.left, r'[^\\s]+$', 0), '|', {shape}))), p -> p is not null)"
    return (
        one.select(F.explode(F.expr(patterns)).alias("pattern"), F.col("c.inst").alias("inst"), (F.col("c.base") | F.col("c.key")).alias("seed"), F.col("c.base").alias("base"))
        .groupBy("pattern", "inst")
        .agg(F.max("seed").alias("seed"), F.max("base").alias("base"))
    )


def vouched(rows: DataFrame, params: PiiParams = PiiParams()) -> DataFrame:
    """Instances beyond the base kinds that confident patterns vouch for: ``(inst, score)``.

    A pattern's confidence is its instances' scores over their number plus the
    damping; an instance's score is one less the product of its patterns' doubts.
    Seeds keep the score 1 as evidence, but are added only if vouched for.
    """
    edges = materialise(_edges(rows), "edges")
    # patterns without enough seeds can never vouch, so they leave the graph first
    held = edges.groupBy("pattern").agg(F.count_if("seed").alias("seeds")).filter(F.col("seeds") >= params.seeds_least)
    edges = materialise(edges.join(held.select("pattern"), "pattern").select("pattern", "inst", F.col("seed").cast("double").alias("score"), F.lit(0.0).alias("vouched"), "seed", "base"), "edges")
    for _ in range(params.rounds):
        confidence = edges.groupBy("pattern").agg((F.sum("score") / (F.count(F.lit(1)) + params.damping)).alias("conf")).filter(F.col("conf") >= params.pattern_least)
        vouch = edges.join(confidence, "pattern").groupBy("inst").agg((1 - F.exp(F.sum(F.log(F.greatest(F.lit(1e-9), 1 - F.col("conf")))))).alias("new"))
        new = F.coalesce("new", F.lit(0.0))
        edges = materialise(edges.join(vouch, "inst", "left").select("pattern", "inst", F.when(F.col("seed"), F.lit(1.0)).otherwise(new).alias("score"), new.alias("vouched"), "seed", "base"), "edges")
    return edges.filter((~F.col("base")) & (F.col("vouched") >= params.instance_least)).groupBy("inst").agg(F.max("vouched").alias("score"))


def find_spans(docs: DataFrame, params: PiiParams = PiiParams()) -> DataFrame:
    """doc_id, ``base`` and ``found`` (discovered) span arrays for every row of ``docs``.

    One pass over the texts; what is kept of them is written to the shared
    folder, and the graph is built from that.  Null or empty texts have no
    spans; rows that repeat a doc_id give one row each; other columns are
    ignored.
    """
    rows = _candidates(base_spans(docs.select("doc_id", "text"))).select("doc_id", F.xxhash64("text").alias("mark"), "base", "cands")
    rows = materialise(rows.withColumn("rid", F.monotonically_increasing_id()), "spans")
    new = vouched(rows.filter("size(cands) > 0"), params)
    found = (
        rows.filter("size(cands) > 0")
        .select("rid", F.explode("cands").alias("c"))
        .filter("not c.base")
        .select("rid", F.expr("named_struct('kind', if(c.key, 'secret', 'other'), 's', c.s, 'e', c.e, 'bs', c.bs, 'be', c.be)").alias("span"), F.col("c.inst").alias("inst"))
        .join(new.select("inst"), "inst")
        .groupBy("rid")
        .agg(F.array_sort(F.collect_list("span")).alias("f"))
    )
    return rows.join(found, "rid", "left").select("doc_id", "mark", "base", F.coalesce("f", F.expr(_NO_SPANS)).alias("found"))


def _joined(spans: str) -> Column:
    return F.expr(f"array_join(transform({spans}, x -> concat(x.kind, ':', x.s, ':', x.e)), ',')")


def pii(docs: DataFrame, params: PiiParams = PiiParams()) -> DataFrame:
    """Counts and digests of the personal data of each row (see ``find_spans``)."""
    out = find_spans(docs, params)
    counts = [F.expr(f"cast(size(filter(base, x -> x.kind = '{k}')) as bigint)").alias(f"n_{k}") for k in KINDS]
    return out.select(
        F.col("doc_id").cast("long").alias("doc_id"), *counts, F.sha2(_joined("base"), 256).alias("base_sha256"), _joined("concat(base, found)").alias("spans"), *[F.expr(f"cast(size(filter(found, x -> x.kind = '{k}')) as bigint)").alias(f"n_{k}") for k in ("secret", "other")],
        F.expr("cast(size(base) + size(found) as bigint)").alias("n_spans"),
    )


def mask(docs: DataFrame, params: PiiParams = PiiParams()) -> DataFrame:
    """``docs`` with each span of personal data replaced by its kind in brackets.

    Of overlapping spans the one that starts first is replaced, the longer one
    at equal starts.  Other columns, clashing names included, stay as they are.
    """
    spans = find_spans(docs, params).filter("size(base) + size(found) > 0").select(F.col("doc_id").alias("_pii_id"), F.col("mark").alias("_pii_mark"), F.concat("base", "found").alias("_pii_spans"))
    spans = spans.dropDuplicates(["_pii_id", "_pii_mark"])
    text = F.coalesce("text", F.lit(""))
    joined = docs.join(spans, F.col("doc_id").eqNullSafe(F.col("_pii_id")) & (F.xxhash64(text) == F.col("_pii_mark")), "left")
    ordered = "transform(array_sort(transform(_pii_spans, x -> named_struct('s', x.s, 'm', -x.e, 'x', x))), y -> y.x)"
    apart = f"""aggregate({ordered}, named_struct('at', 0, 'out', {_NO_SPANS}),
                 (acc, x) -> if(x.s < acc.at, acc, named_struct('at', x.e, 'out', array_append(acc.out, x))), acc -> acc.out)"""
    # cutting bytes does not count characters from the start each time
    parts = "transform(out, (y, i) -> concat(cast(substring(raw, if(i = 0, 0, out[i - 1].be) + 1, y.bs - if(i = 0, 0, out[i - 1].be)) as string), '[', upper(y.kind), ']'))"
    tail = "cast(substring(raw, element_at(out, -1).be + 1) as string)"
    rebuilt = F.expr(_let("raw", "cast(text as binary)", _let("out", apart, f"concat(array_join({parts}, ''), {tail})")))
    return joined.withColumn("text", F.when(F.col("_pii_spans").isNull(), F.col("text")).otherwise(rebuilt)).drop("_pii_id", "_pii_mark", "_pii_spans")


def op5_pii(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Personal data in the whole of ``documents``."""
    return pii(spark.read.parquet(f"{sf_dir}/documents.parquet"))
