"""Toxicity of whole texts: a weighted lexicon matched by Aho-Corasick.

Texts are folded first: lower case, homoglyphs and digit or symbol substitutions
mapped to the letters they imitate.  The lexicon's words and stems and their
weights are learnt from labelled rows; phrases that contain a lexicon word but are no more
toxic than other text become exceptions, which cancel the word's weight.  The
sum of weights is normalised by length and turned into a probability.
"""

from __future__ import annotations

import math
import re
import unicodedata
from collections import Counter
from collections.abc import Iterator
from dataclasses import dataclass, field

import ahocorasick
import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from linkgraph.llm.common import materialise

# Letters that look like Latin ones, and common substitutions.
_LOOKALIKES = {
    "а": "a", "в": "b", "с": "c", "ԁ": "d", "е": "e", "һ": "h", "і": "i", "ј": "j", "к": "k", "ӏ": "i", "м": "m", "н": "h", "о": "o", "р": "p",
    "ԛ": "q", "ѕ": "s", "т": "t", "ц": "u", "у": "y", "ѵ": "v", "ԝ": "w", "х": "x", "α": "a", "β": "b", "ε": "e", "η": "n", "ι": "i", "κ": "k", "ν": "v",
    "ο": "o", "ρ": "p", "τ": "t", "υ": "u", "χ": "x", "ı": "i", "ł": "i",
}
_SUBSTITUTES = {"0": "o", "1": "i", "3": "e", "4": "a", "5": "s", "7": "t", "8": "b"}
#: Stand for letters only between letters.
_SYMBOLS = {"@": "a", "$": "s", "€": "e", "!": "i", "|": "i"}
#: "1", "i" and "l" are one letter after folding, as "1" stands for either.
_ALIKE = {"l": "i"}
_INVISIBLE = dict.fromkeys([0xAD, 0x200B, 0x200C, 0x200D, 0x2060, 0xFEFF])
_FOLD = str.maketrans(_LOOKALIKES | _SUBSTITUTES | _ALIKE) | _INVISIBLE
_FOLD_BYTES = bytes(ord({**_SUBSTITUTES, **_ALIKE}.get(chr(b), chr(b))) for b in range(256))
_INSIDE = re.compile(r"[@$€!|]+(?=[^\W\d_])")
_RUN = re.compile(r"[^\W_]+")


def fold(text: str) -> str:
    """The text as it is matched: lower case, imitated letters put back."""
    low = text.lower()
    try:
        out = low.encode("latin-1").translate(_FOLD_BYTES, b"\xad").decode("latin-1")
    except UnicodeEncodeError:
        low = unicodedata.normalize("NFKC", low)
        out = "".join(c for c in low if not unicodedata.combining(c)) if any(map(unicodedata.combining, set(low))) else low
        out = out.translate(_FOLD)
    return _INSIDE.sub(_as_letters, out)


def _as_letters(m: re.Match) -> str:
    """Symbols after a letter as the letters they stand for."""
    at = m.start()
    return "".join(map(_SYMBOLS.__getitem__, m[0])) if at and m.string[at - 1].isalpha() else m[0]


@dataclass(frozen=True)
class ToxicityParams:
    #: Rows that the lexicon and the curve are fitted on, at most; the rest is scored only.
    max_labelled: int = 6_000
    #: Words of the lexicon, at most; the heaviest are kept.
    max_words: int = 2_000
    #: Rows of label 1 that must hold a word, and its least log-odds.
    min_rows: int = 4
    min_weight: float = 1.5
    #: Lengths of the stems that are tried as entries besides whole words.
    stems: tuple[int, ...] = (4, 5, 6, 7)
    #: Labelled rows that must hold an exception phrase, and its greatest share of label 1.
    min_exception_rows: int = 8
    #: Characters added to every length, so that short texts are not overrated.
    length_floor: int = 200
    threshold: float = 0.3
    #: Phrases that cancel the words in them, besides those that are learnt.
    exceptions: tuple[str, ...] = ()


@dataclass
class ToxicityModel:
    #: Folded words, or stems ending in "*", and their weights.
    words: dict[str, float]
    exceptions: tuple[str, ...] = ()
    #: Constant, slope of the summed weight, slope of the weight by length.
    curve: tuple[float, float, float] = (-4.0, 1.0, 0.0)
    params: ToxicityParams = field(default_factory=ToxicityParams)

    def automaton(self) -> ahocorasick.Automaton:
        entries: dict[str, list] = {}
        for word, weight in self.words.items():
            stem = word.endswith("*")
            entries.setdefault(word[:-1] if stem else word, []).append((weight, stem, False))
        for phrase in (*self.exceptions, *map(fold, self.params.exceptions)):
            if phrase:
                entries.setdefault(phrase, []).append((0.0, False, True))
        found = ahocorasick.Automaton()
        for text, kinds in entries.items():
            found.add_word(text, (len(text), kinds))
        if len(found):
            found.make_automaton()
        return found

    def hits(self, folded: str, found: ahocorasick.Automaton) -> dict[int, tuple[int, float]]:
        """Start of each matched word to the match's end and its greatest weight."""
        best: dict[int, tuple[int, float]] = {}
        if not folded or not len(found):
            return best
        n, spared = len(folded), []
        for end, (length, kinds) in found.iter(folded):
            start = end - length + 1
            if start and folded[start - 1].isalnum():
                continue
            closed = end + 1 == n or not folded[end + 1].isalnum()
            for weight, stem, spare in kinds:
                if not (stem or closed):
                    continue
                if spare:
                    spared.append((start, end))
                elif start not in best or best[start][1] < weight:
                    best[start] = (end, weight)
        if spared:
            best = {s: v for s, v in best.items() if not any(a <= s and v[0] <= b for a, b in spared)}
        return best

    def features(self, text: str, found: ahocorasick.Automaton) -> tuple[float, float]:
        """Summed weight of the matches, and that sum by length."""
        folded = fold(text)
        total = sum(w for _, w in self.hits(folded, found).values())
        return total, total * 1000.0 / (len(folded) + self.params.length_floor)

    def score(self, text: str, found: ahocorasick.Automaton) -> float:
        total, dense = self.features(text, found)
        c, a, b = self.curve
        z = c + a * math.log1p(total) + b * math.log1p(dense)
        return 1.0 / (1.0 + math.exp(-max(-40.0, min(40.0, z))))


class _Tally:
    """Rows of either label that hold each term, written out before it grows large."""

    def __init__(self):
        self.rows = (Counter(), Counter())

    def add(self, terms: set[str], label: int) -> None:
        self.rows[label].update(terms)

    def full(self) -> bool:
        return len(self.rows[0]) + len(self.rows[1]) > 200_000

    def flush(self) -> pa.RecordBatch:
        terms = list(self.rows[0].keys() | self.rows[1].keys())
        out = pa.RecordBatch.from_pydict({"term": pa.array(terms, pa.string()), "n0": pa.array([self.rows[0][w] for w in terms], pa.int64()), "n1": pa.array([self.rows[1][w] for w in terms], pa.int64())})
        self.rows[0].clear(), self.rows[1].clear()
        return out


_TALLIED = "term string, n0 long, n1 long"


def _count_terms(stems: tuple[int, ...]):
    """Words and stems of labelled rows."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally = _Tally()
        for batch in batches:
            for text, label in zip(batch.column("text"), batch.column("toxic").to_pylist(), strict=True):
                words = set(_RUN.findall(fold(text.as_py() or "")))
                terms = set(words)
                for k in stems:
                    terms.update(w[:k] + "*" for w in words if len(w) > k)
                tally.add(terms, label)
                if tally.full():
                    yield tally.flush()
        yield tally.flush()

    return run


def _count_phrases(model: ToxicityModel):
    """Matched words together with the word before or after them."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        tally, found = _Tally(), model.automaton()
        before, after = re.compile(r"[^\W_]+[^\S\n]$"), re.compile(r"[^\W_]*[^\S\n][^\W_]+")
        for batch in batches:
            for text, label in zip(batch.column("text"), batch.column("toxic").to_pylist(), strict=True):
                folded, terms = fold(text.as_py() or ""), set()
                for start, (end, _) in model.hits(folded, found).items():
                    stop = end + 1
                    while stop < len(folded) and folded[stop].isalnum():
                        stop += 1
                    if m := before.search(folded, max(0, start - 40), start):
                        terms.add(folded[m.start() : stop])
                    if m := after.match(folded, end + 1):
                        terms.add(folded[start : m.end()])
                tally.add(terms, label)
                if tally.full():
                    yield tally.flush()
        yield tally.flush()

    return run


def training_rows(docs: DataFrame, labels: DataFrame, params: ToxicityParams) -> DataFrame:
    """At most ``max_labelled`` labelled rows, chosen by a hash of doc_id; held-out ids never."""
    remainder = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4))
    chosen = (
        labels.filter("doc_id is not null and toxic in (0, 1)")
        .filter(remainder != 2)
        .groupBy("doc_id")
        .agg(F.max("toxic").cast("int").alias("toxic"))
        .orderBy(F.xxhash64("doc_id"), "doc_id")
        .limit(params.max_labelled)
    )
    return docs.select("doc_id", "text").join(chosen, "doc_id")


def learn(docs: DataFrame, labels: DataFrame, params: ToxicityParams = ToxicityParams()) -> ToxicityModel:
    """Lexicon, exceptions and curve from the labelled rows that are not held out."""
    train = materialise(training_rows(docs, labels, params), "labelled")
    summed = lambda counted: counted.groupBy("term").agg(F.sum("n0").alias("n0"), F.sum("n1").alias("n1"))
    terms = summed(train.select("text", "toxic").mapInArrow(_count_terms(params.stems), _TALLIED))
    t0, t1 = (int(x or 0) for x in train.agg(F.count_if(F.col("toxic") == 0), F.count_if(F.col("toxic") == 1)).first())
    if not t1:
        return ToxicityModel({}, params=params)
    odds = F.log((F.col("n1") + 0.5) / (t1 + 1.0)) - F.log((F.col("n0") + 0.5) / (t0 + 1.0))
    # a term must stand out beyond chance: a lower bound of its log-odds is its weight
    weight = odds - 1.96 * F.sqrt(1.0 / (F.col("n1") + 0.5) + 1.0 / (F.col("n0") + 0.5))
    heavy = (
        terms.filter(F.col("n1") >= params.min_rows)
        .withColumn("weight", weight)
        .filter(F.col("weight") >= params.min_weight)
        .orderBy(F.desc("weight"), "term")
        .limit(params.max_words)
    )
    words = {r["term"]: float(r["weight"]) for r in heavy.select("term", "weight").collect()}
    model = ToxicityModel(words, params=params)
    if words:
        seen = F.col("n0") + F.col("n1")
        phrases = summed(train.select("text", "toxic").mapInArrow(_count_phrases(model), _TALLIED))
        mild = phrases.filter((seen >= params.min_exception_rows) & (F.col("n1") <= seen * (t1 / (t0 + t1)))).orderBy(F.desc("n0"), "term").limit(params.max_words)
        model.exceptions = tuple(r[0] for r in mild.select("term").collect())
    points = np.array(train.select("text", "toxic").mapInArrow(_features(model), "a double, b double, y int").collect(), dtype=float)  # at most max_labelled rows
    model.curve = fit_curve(points.reshape(-1, 3))
    return model


def fit_curve(points: np.ndarray, rounds: int = 40, ridge: float = 1e-2) -> tuple[float, float, float]:
    """Logistic regression on the logs of both features, by Newton's method."""
    x = np.column_stack([np.ones(len(points)), np.log1p(points[:, 0]), np.log1p(points[:, 1])])
    y, w = points[:, 2], np.zeros(3)
    for _ in range(rounds):
        p = 1 / (1 + np.exp(-np.clip(x @ w, -30, 30)))
        hess = (x * (p * (1 - p))[:, None]).T @ x + ridge * np.eye(3)
        step = np.linalg.solve(hess, x.T @ (y - p) - ridge * w)
        w = w + step
        if np.abs(step).max() < 1e-9:
            break
    return tuple(map(float, w))


def _features(model: ToxicityModel):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = model.automaton()
        for batch in batches:
            got = [model.features(t.as_py() or "", found) for t in batch.column("text")]
            yield pa.RecordBatch.from_pydict({"a": pa.array([g[0] for g in got], pa.float64()), "b": pa.array([g[1] for g in got], pa.float64()), "y": batch.column("toxic").cast(pa.int32())})

    return run


def score(docs: DataFrame, model: ToxicityModel) -> DataFrame:
    """``(doc_id, score)`` for every row of ``docs``; a null text counts as empty."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        found = model.automaton()
        for batch in batches:
            scores = [model.score(t.as_py() or "", found) for t in batch.column("text")]
            yield pa.RecordBatch.from_pydict({"doc_id": batch.column("doc_id").cast(pa.int64()), "score": pa.array(scores, pa.float64())})

    return docs.select("doc_id", "text").mapInArrow(run, "doc_id long, score double")


def toxicity(docs: DataFrame, labels: DataFrame, params: ToxicityParams = ToxicityParams()) -> DataFrame:
    """doc_id, held_out, score and predicted for every row of ``docs``.

    Rows whose doc_id is null are scored, count as not held out, and are never
    learnt from.  Without labelled rows every score is the same low constant.
    """
    scored = score(docs, learn(docs, labels, params))
    held = F.coalesce(F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(4)) == 2, F.lit(False))
    return scored.select("doc_id", held.alias("held_out"), "score", (F.col("score") >= params.threshold).cast("int").alias("predicted"))


def op2_toxicity(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Toxicity of the whole of ``documents``, learnt from ``labels``."""
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return toxicity(docs, spark.read.parquet(f"{sf_dir}/labels.parquet"))
