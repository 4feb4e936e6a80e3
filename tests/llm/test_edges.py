"""Empty tables, nulls, empty and very long texts, repeated rows and clashing columns, for all operators and the pipeline."""

import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

import corpus_pipeline
from linkgraph.llm import ann, bpe, decontaminate, licenses, near_dup, pii, quality, suffix_dedup, toxicity

LONG = " ".join(f"w{k % 9973}" for k in range(60_000))
ROWS = [(1, "a plain text about rivers and things"), (2, None), (3, ""), (4, LONG), (5, "x"), (5, "x"), (5, "another text under the same id"), (None, "a text without an id"), (6, " \n\t ")]


@pytest.fixture(scope="module")
def tables(spark):
    labels = spark.createDataFrame([(1, 1, 0), (4, 0, 1), (None, 1, 1), (9, None, None)], "doc_id long, quality int, toxic int")
    bench = spark.createDataFrame([(1, "name the river that flows through the town"), (2, None), (None, "x")], "item_id long, text string")
    return labels, bench


def operators(labels, bench):
    return {
        "suffix": lambda d: suffix_dedup.suffix_dedup(d, passages=suffix_dedup.PASSAGES),
        "toxicity": lambda d: toxicity.toxicity(d, labels),
        "bpe": bpe.encode,
        "pii": pii.pii,
        "licenses": licenses.licenses,
        "quality": lambda d: quality.resample(d, labels),
        "near_dup": near_dup.near_duplicates,
        "decontaminate": lambda d: decontaminate.contamination(d, bench),
    }


@pytest.mark.parametrize("name", ["suffix", "toxicity", "bpe", "pii", "licenses", "quality", "near_dup", "decontaminate"])
def test_one_row_per_row_and_none_for_none(docs_of, tables, name):
    run = operators(*tables)[name]
    got = run(docs_of(ROWS)).collect()
    assert sorted((r["doc_id"] is None, r["doc_id"] or 0) for r in got) == sorted((i is None, i or 0) for i, _ in ROWS)
    # rows that repeat id and text agree
    alike = [str(r) for r in got if r["doc_id"] == 5]
    assert len(alike) == 3 and len(set(alike)) <= 2 + (name == "quality")
    assert run(docs_of([])).collect() == []


def test_near_dup_of_repeated_and_null_ids(docs_of):
    text = " ".join(f"t{k}" for k in range(40))
    other = " ".join(f"o{k}" for k in range(40))
    rows = [(7, text), (7, other), (3, other + " more"), (None, text), (None, "alone as can be here"), (9, None)]
    got = sorted((r["doc_id"] or 0, r["n_shingles"], r["component_id"] or 0, r["kept"]) for r in near_dup.near_duplicates(docs_of(rows)).collect())
    assert got == sorted([(7, 36, 7, True), (7, 36, 3, False), (3, 37, 3, True), (0, 36, 7, False), (0, 1, 0, True), (9, 0, 9, True)])
    assert sorted((r["doc_id"] or 0, r["text"]) for r in near_dup.keep_first(docs_of(rows)).collect() if r["text"]) == sorted([(7, text), (3, other + " more"), (0, "alone as can be here")])


def test_sketches_of_long_sets_miss_no_pair_at_the_threshold():
    """Blocks pre-judge sets beyond the sketch on it; pairs at exactly the threshold must pass."""
    draw, params = np.random.default_rng(1), near_dup.NearDupParams()
    missed = 0
    for _ in range(400):
        n = int(draw.integers(600, 4000))
        both = -(-6 * n // 7)  # 6/7 of each side in common is a similarity of 0.75
        values = draw.choice(1 << 31, size=2 * n - both, replace=False).astype(np.int64)
        a, b = np.sort(values[:n]), np.sort(np.append(values[:both], values[n:]))
        low_a, low_b = a[: params.sketch], b[: params.sketch]
        last = min(low_a[-1], low_b[-1])
        shared = len(np.intersect1d(low_a, low_b))
        union = np.count_nonzero(low_a <= last) + np.count_nonzero(low_b <= last) - shared
        missed += (shared + 1) * params.sketch < params.sketch_least * (union - 1)
    assert missed == 0


def passages(texts, width=50):
    """Brute force: words of each text in strings of ``width`` words that another text holds."""
    words = [[w.lower() for w in (t or "").split()] for t in texts]
    owners = {}
    for k, ws in enumerate(words):
        for i in range(len(ws) - width + 1):
            owners.setdefault(tuple(ws[i : i + width]), set()).add(k)
    out = []
    for ws in words:
        held = {i + j for i in range(len(ws) - width + 1) if len(owners[tuple(ws[i : i + width])]) > 1 for j in range(width)}
        out.append(len(held))
    return out


def test_passages_against_brute_force(docs_of):
    draw = random.Random(4)
    shared = [[f"p{draw.randrange(400)}" for _ in range(n)] for n in (49, 50, 53, 70, 120)]
    texts = [None, "short"]
    for k in range(60):
        own = lambda: [f"{k}-{draw.randrange(10**6)}" for _ in range(draw.randrange(60))]
        texts.append(" ".join(own() + draw.choice(shared) + own() + (draw.choice(shared)[10:] if k % 3 else []) + own()))
    got = {r["doc_id"]: r["passage_words"] for r in suffix_dedup.suffix_dedup(docs_of(enumerate(texts)), passages=suffix_dedup.PASSAGES).collect()}
    want = passages(texts)
    assert [got[k] for k in range(len(texts))] == want and sum(map(bool, want)) > 30
    many = suffix_dedup.SuffixDedupParams(length=50, gram=25, unit="word", across=True, group_max=2)
    got = {r["doc_id"]: r["passage_words"] for r in suffix_dedup.suffix_dedup(docs_of(enumerate(texts)), passages=many).collect()}
    assert [got[k] for k in range(len(texts))] == want


def plain_total(text, model):
    """Summed weights by searching every entry at every place."""
    folded, best, spared = toxicity.fold(text), {}, []
    at = lambda i: folded[i].isalnum() if 0 <= i < len(folded) else False
    for phrase in model.exceptions:
        spared += [(i, i + len(phrase)) for i in range(len(folded)) if folded.startswith(phrase, i) and not at(i - 1) and not at(i + len(phrase))]
    for entry, weight in model.words.items():
        stem, word = entry.endswith("*"), entry.rstrip("*")
        for i in range(len(folded)):
            if folded.startswith(word, i) and not at(i - 1) and (stem or not at(i + len(word))) and best.get(i, (0, -1.0))[1] < weight:
                best[i] = (i + len(word), weight)
    return sum(w for i, (end, w) in best.items() if not any(a <= i and end <= b for a, b in spared))


def test_toxicity_scores_against_plain_matching(spark, docs_of):
    draw = random.Random(2)
    words = ["rotten", "nasty", "fool", "kind", "friend", "river", "r0tten", "NASTY", "foolish", "f00l.", "(nasty)", "un-kind"]
    neutral = [f"{a}{b}" for a in ("ka", "lo", "mi", "su") for b in ("ren", "tol", "var", "dem", "ish")]
    bad = [int(draw.random() < 0.3) for _ in range(200)]
    texts = ["", *(" ".join(draw.sample(neutral, 6) + ([draw.choice(words[:3]), draw.choice(words)] if k else [draw.choice(words[3:6])]) + draw.sample(neutral, 2)) for k in bad)]
    labels = spark.createDataFrame([*enumerate([0, *bad])], "doc_id long, toxic int")
    docs = docs_of(enumerate(texts))
    model = toxicity.learn(docs, labels)
    assert model.words
    c, a, b = model.curve
    for r in toxicity.toxicity(docs, labels).collect():
        text = texts[r["doc_id"]]
        total = plain_total(text, model)
        dense = total * 1000.0 / (len(toxicity.fold(text)) + model.params.length_floor)
        want = 1 / (1 + np.exp(-np.clip(c + a * np.log1p(total) + b * np.log1p(dense), -40, 40)))
        assert abs(r["score"] - want) < 1e-9 and r["predicted"] == int(r["score"] >= 0.3)


def test_neighbours_of_odd_tables(spark):
    schema = "vec_id long, embedding array<float>, label int, score string"
    same = [0.5, 0.25, 0.0]
    rows = [(0, same, 1, "x"), (1, same, 1, "x"), (2, same, 1, "x"), (3, None, 1, "x"), (4, [0.0, 0.0, 0.0], 1, "x"), (5, [float("nan"), 1.0, 0.0], 1, "x"), (6, [0.0, 1.0, 0.0], 1, "x")]
    got = [tuple(r)[:4] for r in ann.nearest(spark.createDataFrame(rows, schema), F.col("vec_id") % 50 == 0).orderBy("query_id", "rank").collect()]
    assert [(q, r, v) for q, r, v, _ in got] == [(0, 1, 1), (0, 2, 2), (0, 3, 6)] and abs(got[0][3] - 1.0) < 1e-12
    assert ann.nearest(spark.createDataFrame([], schema), F.col("vec_id") % 50 == 0).collect() == []


def test_pipeline_stages(spark, tmp_path):
    draw = random.Random(8)
    text = lambda: " ".join(f"w{draw.randrange(500)}" for _ in range(60))
    item = "in the year of the flood the old miller counted all the sacks of grain that his sons had carried over the bridge"
    first = text()
    rows = [(1, first), (2, first), (3, first + " tail"), (4, f"{text()} {item} {text()}"), (5, None), (6, ""), (7, "mail a@b.org " + text()), (8, text()), (None, text()), (8, text())]
    docs = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, 1, 0)], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")
    spark.createDataFrame([(1, item)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    now = docs
    kept = {"toxicity": [None, 1, 2, 3, 4, 5, 6, 7, 8, 8], "near_dedup": [None, 1, 4, 5, 6, 7, 8, 8], "decontamination": [None, 1, 5, 6, 7, 8, 8], "pii": [None, 1, 5, 6, 7, 8, 8]}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        now = stage(spark, now, str(tmp_path))
        assert now.columns == docs.columns
        assert sorted((r["doc_id"] for r in now.collect()), key=lambda i: (i is not None, i)) == kept[name], name
    assert [r["text"][:13] for r in now.collect() if r["doc_id"] == 7] == ["mail [EMAIL] "]
    out = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert sorted((r["doc_id"] for r in out), key=lambda i: (i is not None, i)) == kept["pii"]
    assert {r["decoded_sha256"] for r in out if r["doc_id"] in (5, 6)} == {hashlib.sha256(b"").hexdigest()}
    docs.limit(0).write.parquet(f"{tmp_path}/none/documents.parquet")
    for table in ("labels", "benchmark"):
        spark.read.parquet(f"{tmp_path}/{table}.parquet").limit(0).write.parquet(f"{tmp_path}/none/{table}.parquet")
    assert corpus_pipeline.run(spark, f"{tmp_path}/none").collect() == []
