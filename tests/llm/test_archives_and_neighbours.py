"""Archive round trips and neighbour search against brute force."""

import hashlib

import numpy as np
from pyspark.sql import functions as F

from linkgraph.llm.ann import AnnParams, nearest, probe_order
from linkgraph.llm.warc import archive_stream, round_trip, write_archive


def test_round_trip(spark):
    big = "é\r\n\r\n" * 5000
    rows = [(3, "http://a b", big), (1, None, big), (2, "u", "short"), (4, "u", "short"), (5, "u", None), (6, "u", ""), (7, "u", "WARC/1.1\r\n\r\n" + "x" * 200)]
    pages = spark.createDataFrame([(*r, 0) for r in rows], "page_id long, url string, html string, chunk int")
    for chunk in (1 << 20, 1000):
        got = {r["page_id"]: tuple(r)[1:] for r in round_trip(pages, chunk).collect()}
        sha = lambda t: hashlib.sha256((t or "").encode()).hexdigest()
        assert got == {i: (len((t or "").encode()), sha(t), "revisit" if i == 3 else "response", 1 if i == 3 else None) for i, _, t in rows}
    assert round_trip(pages.limit(0)).count() == 0
    stream = b"".join(archive_stream(write_archive(pages, 1000)))
    assert stream.count(b"WARC-Record-ID: ") == len(rows) and stream.startswith(b"WARC/1.1\r\n")


def test_probe_order_is_by_cost():
    inside = np.array([0.1, 0.6, 0.45])
    cost = lambda change: sum(inside[k] ** 2 if s < 0 else (1 - inside[k]) ** 2 for k, s in change)
    order = probe_order(inside, 15)
    assert order[0] == () and len(set(order)) == len(order)
    costs = [cost(c) for c in order]
    assert costs == sorted(costs)


def test_neighbours(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(400, 16)).astype(np.float32)
    x[100:160] = x[100]  # one common vector
    rows = [(i, [float(v) for v in r]) for i, r in enumerate(x)] + [(900, None), (950, [0.0] * 16), (1000, [float("nan")] * 16), (1050, [1.0, None] * 8), (1100, [])]
    out = nearest(spark.createDataFrame(rows, "vec_id long, embedding array<float>"), F.pmod("vec_id", F.lit(50)) == 0, AnnParams(bucket_target=40, block=32)).collect()
    found: dict[int, list] = {}
    for r in sorted(out, key=lambda r: (r["query_id"], r["rank"])):
        found.setdefault(r["query_id"], []).append((r["vec_id"], r["score"]))
    assert set(found) == {0, 50, 100, 150, 200, 250, 300, 350}
    y = x.astype(np.float64)
    size = np.linalg.norm(y, axis=1)
    hits = 0
    for q, got in found.items():
        s = y @ y[q] / (size * size[q])
        s[q] = -2
        best = sorted(range(400), key=lambda i: (-round(s[i], 12), i))[:5]
        hits += len({i for i, _ in got} & set(best))
        assert all(abs(s[i] - v) < 1e-9 for i, v in got)
    assert hits >= 0.9 * 40
    assert [i for i, _ in found[100]] == [101, 102, 103, 104, 105] and [i for i, _ in found[150]] == [100, 101, 102, 103, 104]


def test_recall_does_not_fall_with_the_hashes(spark):
    """Small buckets, as if the table were a few hundred times larger."""
    rng = np.random.default_rng(5)
    x = rng.normal(size=(1500, 64))
    x /= np.linalg.norm(x, axis=1)[:, None]
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    params = AnnParams(bucket_target=1)
    out = nearest(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.pmod("vec_id", F.lit(50)) == 0, params).collect()
    score = x @ x.T
    np.fill_diagonal(score, -2)
    hits = sum(r["vec_id"] in set(np.argsort(-score[r["query_id"]])[:5]) for r in out)
    assert params.hashes(1500) == 6 and hits >= 0.9 * 30 * 5
