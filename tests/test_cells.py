"""Graphs in cells of a grid: equal to the dense solution however cut up, and no frame of a graph's edges as text."""

import numpy as np
import pytest

from walkrank.operators import baselines, cells, prepare, walk
from walkrank.plans import methods
from walkrank.sources import graphs


@pytest.mark.parametrize("cell, block, deal, tol", [(cells.CELL, cells.BLOCK, cells.DEAL, 1e-12), (256, 40, 100, 1e-5)])
def test_converged_in_cells(spark, monkeypatch, cell, block, deal, tol):
    for name, v in (("CELL", cell), ("BLOCK", block), ("DEAL", deal)):
        monkeypatch.setattr(cells, name, v)
    pairs = np.random.default_rng(0).integers(0, 60, (700, 2))
    pairs = [(int(a) - 30, (int(b) - 30) * 10**15) for a, b in pairs if a != b] + [(7, int(x) * 10**15) for x in range(-30, 30)]  # targets beside 0 have no out-edges
    pairs += [(b, a) for a, b in pairs[:300]] * 3
    codes = sorted({x for e in pairs for x in e})
    p = np.zeros((len(codes), len(codes)))
    for a, b in pairs:
        p[codes.index(b), codes.index(a)] = 1
    idle = p.sum(axis=0) == 0
    p[idle, idle] = 1
    assert idle.any()
    dense = np.linalg.solve(np.eye(len(codes)) - 0.85 * p / p.sum(axis=0), np.full(len(codes), 0.15 / len(codes)))
    edges = spark.createDataFrame(pairs, "src long, dst long").repartition(3)
    got = baselines.converged(edges, tol=tol, once=True, stay=True).orderBy("code").collect()
    assert [r.code for r in got] == codes and np.allclose([r.value for r in got], dense, atol=10 * tol, rtol=0)
    assert baselines.converged(edges.limit(0)) is None


def tables(spark, d, lines, orders):
    spark.createDataFrame(lines, "l_orderkey long, l_partkey long, l_suppkey long, l_linenumber int").write.parquet(f"{d}/lineitem.parquet")
    spark.createDataFrame(orders, "o_orderkey long, o_custkey long").write.parquet(f"{d}/orders.parquet")
    return str(d)


def test_trade_reference_holds_no_edges(spark, tmp_path, monkeypatch):
    r = np.random.default_rng(1)
    lines = [(int(o), int(p), int(s), i) for i, (o, p, s) in enumerate(zip(r.integers(0, 300, 3000), r.integers(0, 40, 3000), r.integers(-2, 8, 3000)))]
    lines += [(1, None, 3, 0), (2, 5, None, 0), (999, 1, 1, 0), (300, None, 9, 0)]
    d = tables(spark, tmp_path, lines, [(o, o % 25) for o in range(300)] + [(300, 77), (5, None)])  # who is customer 77 has no out-edge
    e = prepare.repair(graphs.trade(spark, d)).collect()
    ids = sorted({x for row in e for x in row})
    p = np.zeros((len(ids), len(ids)))
    for a, b in e:
        p[ids.index(b), ids.index(a)] = 1
    dense = np.linalg.solve(np.eye(len(ids)) - 0.85 * p / p.sum(axis=0), np.full(len(ids), 0.15 / len(ids)))
    held = []
    for module in (baselines, methods):
        monkeypatch.setattr(module, "cut", lambda df, cut=module.cut: held.append((out := cut(df)).count()) or out)
    got = methods.reference(spark, d, "trade").orderBy("id").collect()
    assert [x.id for x in got] == ids and np.allclose([x.value for x in got], dense, atol=1e-12, rtol=0)
    assert held and max(held) <= len(ids) < len(e)


def test_trade_layout_holds_no_edges(spark, tmp_path, monkeypatch):
    r = np.random.default_rng(2)
    lines = [(int(o), int(p), int(s), i) for i, (o, p, s) in enumerate(zip(r.integers(0, 300, 3000), r.integers(0, 40, 3000), r.integers(-2, 8, 3000)))]
    d = tables(spark, tmp_path, lines + [(300, None, 3, 0)], [(o, o % 25) for o in range(300)] + [(300, 77)])
    p = walk.WalkParams(n_walkers=8, horizon=2, refresh_rate=0.7, rng=methods.RNG, counters=False)
    want = sorted(map(tuple, walk.walker_tally(methods.placed(spark, d, "trade"), p).tally.collect()))
    held, edges = [], graphs.trade(spark, d).count()
    monkeypatch.setattr(graphs, "cut", lambda df, cut=graphs.cut: held.append((out := cut(df)).count()) or out)
    made = []
    monkeypatch.setattr(walk, "walker_tally", lambda lay, *a, f=walk.walker_tally: made.append(lay) or f(lay, p))
    methods.Q["experiment_accuracy_k"](spark, d)
    assert made[0].near is not None and made[0].replicas is None  # not laid out whole
    assert sorted(map(tuple, walk.walker_tally(made[0], p).tally.collect())) == want
    assert max(held) < edges
