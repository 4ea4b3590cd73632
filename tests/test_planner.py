import pytest

from vecpath.plans import planner, published
from vecpath.plans.planner import IndexInfo, Workload


def test_model_orders_the_paths_as_measured():
    model, cells = planner.default_model(), {}
    for s, b, d, path, ms in published.filter_rows():
        cells.setdefault((s, b, d), {})[path] = ms
    right = pairs = 0
    for (s, b, d), ms in cells.items():
        got = {p: model.cost(p, Workload(1_000_000, d, b, s / 100)) for p in ms}
        for p in ms:
            for q in ms:
                if p < q and max(ms[p], ms[q]) > 1.5 * min(ms[p], ms[q]):
                    pairs += 1
                    right += (ms[p] < ms[q]) == (got[p] < got[q])
    assert right >= 0.95 * pairs


def test_model_moves_the_crossing_as_measured():
    """Many qualifying rows favour the graph; larger batches favour scanning longer."""
    for b, d in published.FILTER_MS:
        few = planner.choose_path(Workload(1_000_000, d, b, 0.01), IndexInfo("cosine"))
        many = planner.choose_path(Workload(1_000_000, d, b, 1.0), IndexInfo("cosine"))
        assert few.path != "graph" and many.path == "graph"
    cross = {}
    for key, paths in published.FILTER_MS.items():
        best = [min(a, b) for a, b in zip(paths["scan"], paths["matrix"])]
        cross[key] = planner.crossover(published.SCAN_PERCENT, paths["graph"], best)
    assert cross[1, 64] < cross[1, 1024] and cross[10000, 64] < cross[10000, 1024]
    assert cross[1, 64] < cross[10000, 64] and cross[1, 1024] < cross[10000, 1024]


def test_relational_rule_is_the_other_way_round():
    few, many = published.RELATIONAL_MS[0.1], published.RELATIONAL_MS[50]
    assert few[1] < few[0] and many[1] > many[0] and few[3] < few[2] and many[3] > many[2]


def test_filtering_dominates_small_batches_and_products_large_ones():
    for (_, b, _), (_, copying, computing) in published.PHASES.items():
        assert abs(sum(published.PHASES[64, 1, 10]) - 100) < 0.3
        assert copying > computing if b < 10000 else computing > copying


def test_hard_rules():
    w = Workload(1000, 8, metric="ip")
    assert planner.choose_path(w, IndexInfo()).reason == "no index"
    assert planner.choose_path(w, IndexInfo("l2")).reason == "metric differs from the index"
    assert planner.capabilities(IndexInfo("ip", fresh=False), w)[0] == ("scan", "matrix")
    with pytest.raises(ValueError):
        planner.choose_path(w, IndexInfo(), hint="graph")
    assert planner.choose_path(w, IndexInfo("ip"), hint="graph").path == "graph"
    assert "hint" in planner.choose_path(w, IndexInfo("ip"), hint="scan").explain()


def test_kernel_choice_is_not_monotone_in_the_dimension():
    assert [planner.choose_kernel(1, d) for d in (64, 256, 1024)] == ["plain", "vector", "vector"]
    assert [planner.choose_kernel(100, d) for d in (64, 256, 1024)] == ["matrix", "matrix", "vector"]
    assert {planner.choose_kernel(10000, d) for d in (64, 256, 1024)} == {"matrix"}


def test_cost_model_beats_every_static_policy():
    times = {}
    for s, b, d, path, ms in published.filter_rows():
        times.setdefault((s, b, d), {})[path] = ms
    chosen = {c: planner.choose_path(Workload(1_000_000, c[2], c[1], c[0] / 100), IndexInfo("cosine")).path for c in times}
    mean = lambda r: sum(r.values()) / len(r)
    mine = planner.regret(times, chosen)
    assert max(mine.values()) <= 3
    for path in planner.PATHS:
        assert mean(mine) < mean(planner.regret(times, dict.fromkeys(times, path)))


def test_crossover():
    assert abs(planner.crossover([1, 100], [1, 100], [10, 10]) - 10) < 1e-9
    assert planner.crossover([1, 10], [1, 2], [5, 6]) is None


def test_adaptive_refits_once_it_has_seen_enough():
    a = planner.Adaptive()
    assert not a.refit(1_000_000)
    a.measured = [(s, b, d, p, ms / 2) for s, b, d, p, ms in published.filter_rows()]
    assert a.refit(1_000_000)
    w = Workload(1_000_000, 64, 1, 0.5)
    assert a.model.cost("scan", w) < planner.default_model().cost("scan", w)
