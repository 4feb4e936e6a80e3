"""The registered experiments run whole."""

import pytest

from linkgraph.params import Params
from linkgraph.plans import catalog
from linkgraph.plans import workloads as w


def test_registered_runs_are_whole(monkeypatch):
    seen = []
    monkeypatch.setattr(w, "cut_pair", lambda spark, d, cut: cut)
    monkeypatch.setattr(w, "confusable", lambda spark, d: "LX")
    monkeypatch.setattr(w.plans, "experiment", lambda spark, pair, p: seen.append((pair, p)))
    monkeypatch.setattr(w.plans, "ablate", lambda spark, pair, p: seen.append((pair, p)))
    for name, pair in [(f"wl_{k}", cut) for k, cut in w.CUTS.items()] + [("wl_confusable", "LX"), ("wl_ablation", w.CUTS["A"])]:
        w.QUERIES[name][0](None, "")
        assert seen.pop() == (pair, w.RUN)


class _Scores:
    def collect(self):
        return [{"method": "CG", "task": "SM", "f1": 1.0}]


def test_sweep_is_whole(monkeypatch):
    cuts = []
    monkeypatch.setattr(w, "cut_pair", lambda spark, d, cut: cuts.append(cut))
    monkeypatch.setattr(w.plans, "experiment", lambda spark, pair, p: _Scores())

    class Session:
        def createDataFrame(self, rows, schema):
            return rows

    rows = w.QUERIES["wl_missing_sweep"][0](Session(), "")
    assert len(rows) == len(cuts) == 49 and max(r[1] for r in rows) == max(r[2] for r in rows) == 0.5
    assert {r[0] for r in w.QUERIES["wl_missing_patterns"][0](Session(), "")} == set(w.PATTERNS)
    assert {(c.rows, c.shared_rows) for c in cuts} == {(777, 55)}


def test_link_queries_use_all_parameters(monkeypatch):
    seen = []

    def link(spark, pair, p, cost=False):
        seen.append(p)
        raise InterruptedError

    monkeypatch.setattr(catalog, "_pair", lambda spark, d: None)
    monkeypatch.setattr(catalog.plans, "link", link)
    for name in ("link_natural", "link_tripartite"):
        with pytest.raises(InterruptedError):
            catalog.QUERIES[name][0](None, "")
    assert seen == [Params(), Params().tripartite()]


def test_cells_of_the_sweep_go_at_once(monkeypatch):
    import threading

    met = threading.Barrier(2, timeout=20)
    monkeypatch.setattr(w, "cut_pair", lambda spark, d, cut: cut)
    monkeypatch.setattr(w.plans, "experiment", lambda spark, pair, p: met.wait() < 2 and _Scores())

    class Session:
        def createDataFrame(self, rows, schema):
            return rows

    assert [r[1:3] for r in w.missing_sweep(Session(), "", (0.1, 0.2))] == [(0.1, 0.1), (0.1, 0.2), (0.2, 0.1), (0.2, 0.2)]


def test_settings_of_the_ablation_go_at_once(monkeypatch):
    import threading

    met = threading.Barrier(2, timeout=20)

    class Result:
        def release(self):
            met.wait()

    class Rows:
        def select(self, *_):
            return self

        def collect(self):
            return [("SM", 1.0, 1.0, 1.0)]

    class Session:
        def createDataFrame(self, rows, schema):
            return rows

    monkeypatch.setattr(w.plans, "matched", lambda spark, pair, p: Result())
    monkeypatch.setattr(w.plans, "scored", lambda *_: Rows())
    pair = w.TablePair((), ())
    rows = w.plans.ablate(Session(), pair)
    assert len(rows) == 14 and rows[0][0] == "edges=1 merge=1 weights=1" and rows[-1][0] == "without c_f"


def test_rows_of_a_pair_and_its_profile_are_made_once(spark, monkeypatch):
    from dataclasses import replace

    from linkgraph.operators import colsim
    from linkgraph.sources import bases

    sf, read, made, base, profile = "/root/testdata/sf0.001", spark.sparkContext.accumulator(0), spark.sparkContext.accumulator(0), bases.base, colsim.profile

    def counted(df, n):
        def run(frames):
            for f in frames:
                n.add(len(f))
                yield f

        return df.mapInPandas(run, df.schema)

    def counted_base(*where):
        df, key = base(*where)
        return counted(df, read), key

    monkeypatch.setattr(bases, "base", counted_base)
    monkeypatch.setattr(colsim, "profile", lambda pair: counted(profile(pair), made))
    pair = w.workload(spark, sf, "K", scale=0.2)
    result = w.plans.matched(spark, pair, replace(w.RUN, walks_per_node=1, dim=16))
    assert {r["task"] for r in w.plans.scored(spark, pair, result, "CG").collect()} == {"SM", "ER"}
    assert (pair.tables[0].count(), pair.tables[1].count(), pair.true_records.count()) == (50, 50, 10)
    result.release()
    assert read.value == base(spark, sf, "BC")[0].count()
    assert made.value == len(pair.columns(0)) + len(pair.columns(1))
