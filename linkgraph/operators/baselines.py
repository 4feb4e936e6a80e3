"""Baselines and controls besides the graph methods."""

from __future__ import annotations

import re
from collections.abc import Callable

import numpy as np
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from linkgraph.functions.similarity import name_similarity
from linkgraph.operators import colsim
from linkgraph.params import Params
from linkgraph.sources.pairs import TablePair

Completer = Callable[[str], str]


def match_rules(spark: SparkSession, pair: TablePair, p: Params = Params(), least: float = 0.55) -> DataFrame:
    """Rule control: columns of one class whose names and statistics agree well enough; mutual best."""
    prof = colsim.profile(pair)
    klass = prof.select("cid", "klass")
    sim = colsim.column_similarity(spark, pair, p, prof)
    same = sim.join(klass.select(F.col("cid").alias("left_cid"), F.col("klass").alias("lk")), "left_cid").join(klass.select(F.col("cid").alias("right_cid"), F.col("klass").alias("rk")), "right_cid").filter("lk = rk")
    score = (F.col("s_lev") + F.col("s_diff")) / 2
    from linkgraph.operators.match import select_matches

    return select_matches(same.select(F.col("left_cid").alias("left_key"), F.col("right_cid").alias("right_key"), score.alias("score")), "mutual_best", least)


def match_lexicon(spark: SparkSession, pair: TablePair, synonyms: DataFrame) -> DataFrame:
    """Lexicon control: columns whose name parts agree after replacing synonyms (word, concept)."""
    meta = colsim.scanned_metadata(spark, pair)
    parts = meta.select("side", "cid", F.explode(F.array_distinct(F.split(F.lower("name"), "[^a-z0-9]+"))).alias("word")).filter("length(word) > 1")
    concepts = parts.join(F.broadcast(synonyms), "word", "left").select("side", "cid", F.coalesce("concept", "word").alias("c")).distinct()
    sizes = concepts.groupBy("cid").agg(F.count(F.lit(1)).alias("n"))
    a, b = concepts.filter("side = 0"), concepts.filter("side = 1")
    both = a.select(F.col("cid").alias("left_key"), "c").join(b.select(F.col("cid").alias("right_key"), "c"), "c").groupBy("left_key", "right_key").agg(F.count(F.lit(1)).alias("n"))
    both = both.join(sizes.select(F.col("cid").alias("left_key"), F.col("n").alias("nl")), "left_key").join(sizes.select(F.col("cid").alias("right_key"), F.col("n").alias("nr")), "right_key")
    return both.filter("2 * n >= least(nl, nr) * 2").select("left_key", "right_key", F.round(2 * F.col("n") / (F.col("nl") + F.col("nr")), 6).alias("score"))


def agreement_patterns(pair: TablePair, candidates: DataFrame) -> DataFrame:
    """(left_key, right_key, pattern): per true column pair, 1 agree, 0 differ, x missing."""
    from linkgraph.operators.prepare import canonical

    def side(s: int, columns: list[str]) -> DataFrame:
        t = pair.tables[s]
        fields = {f.name: f for f in t.schema.fields}
        return t.select(F.concat(F.lit(f"{s}:"), F.col(f"`{pair.keys[s]}`").cast("string")).alias("left_key" if s == 0 else "right_key"), *[canonical(fields[c]).alias(f"{'lr'[s]}{k}") for k, c in enumerate(columns)])

    left, right = side(0, [a for a, _ in pair.true_columns]), side(1, [b for _, b in pair.true_columns])
    joined = candidates.join(left, "left_key").join(right, "right_key")
    letter = lambda k: F.when(F.col(f"l{k}").isNull() | F.col(f"r{k}").isNull(), "x").when(F.col(f"l{k}") == F.col(f"r{k}"), "1").otherwise("0")
    return joined.select("left_key", "right_key", F.concat(*[letter(k) for k in range(len(pair.true_columns))]).alias("pattern"))


def fit_linkage(patterns: list[tuple[str, int]], rounds: int = 50) -> tuple[np.ndarray, np.ndarray, float]:
    """EM for the agreement rates of matches and of non-matches, from pattern counts."""
    codes = np.array([[{"1": 1.0, "0": 0.0, "x": np.nan}[c] for c in pat] for pat, _ in patterns])
    n = np.array([c for _, c in patterns], float)
    known, agree = ~np.isnan(codes), np.nan_to_num(codes)
    m, u, share = np.full(codes.shape[1], 0.9), np.full(codes.shape[1], 0.1), 0.05
    for _ in range(rounds):
        like = lambda q: np.exp((known * (agree * np.log(q) + (1 - agree) * np.log(1 - q))).sum(1))
        a, b = share * like(m), (1 - share) * like(u)
        g = a / np.maximum(a + b, 1e-300)
        share = float(np.clip((g * n).sum() / n.sum(), 1e-6, 1 - 1e-6))
        rate = lambda w: np.clip(((w * n)[:, None] * agree).sum(0) / np.maximum(((w * n)[:, None] * known).sum(0), 1e-9), 1e-4, 1 - 1e-4)
        m, u = rate(g), rate(1 - g)
    return m, u, share


def match_linkage(spark: SparkSession, pair: TablePair, candidates: DataFrame, rounds: int = 50) -> DataFrame:
    """Probabilistic linkage control: log-weights of agreements, fitted on pattern counts."""
    pats = agreement_patterns(pair, candidates)
    counts = [(r[0], r[1]) for r in pats.groupBy("pattern").agg(F.count(F.lit(1))).collect()]  # at most 3**columns rows
    if not counts:
        return spark.createDataFrame([], "left_key string, right_key string, score double")
    m, u, share = fit_linkage(counts, rounds)
    weight = {pat: float(np.log(share / (1 - share)) + sum(np.log(m[k] / u[k]) if c == "1" else np.log((1 - m[k]) / (1 - u[k])) if c == "0" else 0.0 for k, c in enumerate(pat))) for pat, _ in counts}
    table = spark.createDataFrame(list(weight.items()), "pattern string, score double")
    from linkgraph.operators.match import select_matches

    return select_matches(pats.join(F.broadcast(table), "pattern").select("left_key", "right_key", "score"), "mutual_best", 0.0)


def render_schema_prompt(pair: TablePair, samples: dict[tuple[int, str], list[str]] | None = None) -> str:
    """A request to list the corresponding columns of both tables, in a fixed answer form."""
    lines = ["Two tables describe partly the same things.", "Name every column of table L that means the same as a column of table R.", "Answer with one pair a line, as: L.column = R.column", ""]
    for s, tag in ((0, "L"), (1, "R")):
        lines.append(f"Table {tag}:")
        for c in pair.columns(s):
            told = pair.descriptions.get((s, c))
            shown = (samples or {}).get((s, c))
            lines.append(f"- {c}" + (f" ({told})" if told else "") + (f"; for example {', '.join(shown)}" if shown else ""))
    return "\n".join(lines)


def typical_values(pair: TablePair, k: int = 3) -> dict[tuple[int, str], list[str]]:
    """The ``k`` most frequent values of each column, ties to the smaller one; what a prompt shows of the data."""
    from linkgraph.operators.prepare import cells

    counts = cells(pair).filter("not is_missing").groupBy("side", "cid", "val").agg(F.count(F.lit(1)).alias("n"))
    best = counts.withColumn("r", F.row_number().over(Window.partitionBy("side", "cid").orderBy(F.desc("n"), "val"))).filter(F.col("r") <= k)
    out: dict[tuple[int, str], list[str]] = {}
    for r in best.orderBy("side", "cid", "r").collect():  # k rows a column
        out.setdefault((r["side"], r["cid"].split(":", 1)[1]), []).append(re.sub(r"\s+", " ", r["val"]))
    return out


def parse_schema_answer(answer: str, pair: TablePair) -> list[tuple[str, str]]:
    """Column pairs of an answer; names that a table lacks are ignored."""
    found = re.findall(r"L\.([^\s=]+)\s*=\s*R\.([^\s,;]+)", answer)
    left, right = set(pair.columns(0)), set(pair.columns(1))
    return list(dict.fromkeys((f"0:{a}", f"1:{b}") for a, b in found if a in left and b in right))


def prompt_schema_match(spark: SparkSession, pair: TablePair, complete: Completer, sample_rows: int = 0) -> DataFrame:
    samples = typical_values(pair, sample_rows) if sample_rows else None
    rows = parse_schema_answer(complete(render_schema_prompt(pair, samples)), pair)
    return spark.createDataFrame(rows, "left_key string, right_key string")


def render_entity_prompt(records: list[tuple[str, str]]) -> str:
    head = "For each numbered pair of records say whether both describe the same thing. Answer with one line a pair, as: number yes or number no."
    return "\n".join([head, *(f"{k}. {a} || {b}" for k, (a, b) in enumerate(records, 1))])


def parse_entity_answer(answer: str, n: int) -> list[bool]:
    said = {int(k): v.lower() == "yes" for k, v in re.findall(r"(\d+)\W+(yes|no)\b", answer, re.I)}
    return [said.get(k, False) for k in range(1, n + 1)]


def prompt_entity_match(pair: TablePair, candidates: DataFrame, complete: Completer, batch: int = 20) -> DataFrame:
    """Candidate record pairs that the completer accepts, asked in batches where the data is."""
    import pandas as pd

    def text(s: int) -> DataFrame:
        t = pair.tables[s]
        key = "left_key" if s == 0 else "right_key"
        return t.select(F.concat(F.lit(f"{s}:"), F.col(f"`{pair.keys[s]}`").cast("string")).alias(key), F.to_json(F.struct(*[F.col(f"`{c}`") for c in pair.columns(s)])).alias(f"t{s}"))

    def run(frames):
        for f in frames:
            for lo in range(0, len(f), batch):
                part = f.iloc[lo : lo + batch]
                good = parse_entity_answer(complete(render_entity_prompt(list(zip(part.t0, part.t1, strict=True)))), len(part))
                yield pd.DataFrame({"left_key": part.left_key[good], "right_key": part.right_key[good]})

    return candidates.join(text(0), "left_key").join(text(1), "right_key").select("left_key", "right_key", "t0", "t1").mapInPandas(run, "left_key string, right_key string")


class StubCompleter:
    """Answers by a rule, to exercise rendering and parsing.  It is no language model, and
    its scores say nothing about one."""

    def __call__(self, prompt: str) -> str:
        if "Table L:" in prompt:
            left, right = prompt.split("Table R:")
            names = lambda text: re.findall(r"^- (\S+)", text, re.M)
            part = lambda n: n.lower().split("_")[-1]
            by = {part(n): n for n in names(right)}
            return "\n".join(f"L.{a} = R.{by[part(a)]}" for a in names(left) if part(a) in by)
        out = []
        for k, a, b in re.findall(r"^(\d+)\. (.*) \|\| (.*)$", prompt, re.M):
            x, y = (set(re.findall(r"\w+", t.lower())) for t in (a, b))
            out.append(f"{k} {'yes' if len(x & y) * 2 > min(len(x), len(y)) else 'no'}")
        return "\n".join(out)


def lexically_close(spark: SparkSession, pair: TablePair, least: float = 0.6) -> DataFrame:
    """Column pairs whose names are close, for the analysis of confusable names."""
    meta = colsim.scanned_metadata(spark, pair)
    a, b = meta.filter("side = 0").select(F.col("cid").alias("left_key"), F.col("name").alias("l")), meta.filter("side = 1").select(F.col("cid").alias("right_key"), F.col("name").alias("r"))
    out = a.join(F.broadcast(b)).withColumn("s_lev", name_similarity(F.col("l"), F.col("r"))).filter(F.col("s_lev") >= least)
    return out.withColumn("rank", F.row_number().over(Window.partitionBy("left_key").orderBy(F.desc("s_lev"), "right_key"))).select("left_key", "right_key", F.round("s_lev", 6).alias("s_lev"), "rank")
