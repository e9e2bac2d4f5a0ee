import math
import random
from fractions import Fraction

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from pipeflow.plans import cost, memory, order, phases, progress, validate
from pipeflow.plans.graph import BLOCKING, INPUT, OUTPUT, PULL, PUSH, Edge, FlowGraph, FlowGraphError, delay_graph, regrid_graph


def test_regrid_graph_counts():
    g = regrid_graph()
    kinds = [e.kind for e in g.edges]
    assert (len(g.nodes), len(g.edges), kinds.count(PUSH), kinds.count(PULL), kinds.count(BLOCKING)) == (10, 9, 6, 1, 2)
    assert phases.order(g) == [["src", "map", "S1i"], ["S1o", "rd", "co", "S2i"], ["S2o", "emit", "wr"]]


def test_regrid_orders():
    g = regrid_graph()
    p = phases.order(g)
    assert order.describe(g, p[0]) == ["src", "map", "S1i"] and order.open(g, p[0]) == ["S1i", "map", "src"]
    assert order.initiators(g, p[0]) == ["src"] and order.initiators(g, p[1]) == ["rd"] and order.initiators(g, p[2]) == ["S2o"]
    assert order.open(g, p[1]) == ["S1o", "S2i", "co", "rd"] and order.close(g, p[1]) == ["rd", "co", "S2i", "S1o"]


def test_delay_repair():
    g = delay_graph()
    assert validate.self_blocked(g) == ["S"] and not validate.phase_cycle(g)
    with pytest.raises(FlowGraphError, match="self_blocked"):
        phases.order(g)
    active, passive = phases.insert_delays(g), phases.insert_delays(g, pulled=True)
    assert len(phases.order(active)) == len(phases.order(passive)) == 2
    assert set(phases.order(active)[0]) == {"u", "Si", "D1i"}
    assert order.initiators(active, phases.order(active)[1]) == ["D1o"]
    assert order.initiators(passive, phases.order(passive)[1]) == ["w"]


def test_invalid_graphs():
    mixed = FlowGraph().node("a").node("b").node("c").push("a", "b").pull("a", "c")
    loop = FlowGraph().node("a").node("b").push("a", "b", "a")
    crossed = FlowGraph().blocking("P").blocking("R").push("Pi", "Ro").push("Po", "Ri")
    lone = FlowGraph().node("i", INPUT, "X").node("a").push("a", "i")
    for g, rule in ((mixed, "mixed_out"), (loop, "acyclic"), (crossed, "phase_cycle|acyclic"), (lone, "block_pairs"), (delay_graph(), "self_blocked")):
        with pytest.raises(FlowGraphError, match=rule):
            validate.check(g)
    assert phases.order(FlowGraph().node("a")) == [["a"]]


def dag(seed: int) -> FlowGraph:
    r = random.Random(seed)
    g = FlowGraph()
    n = r.randint(1, 8)
    out = []
    for i in range(n):
        if r.random() < 0.4:
            g.blocking(f"b{i}")
            out.append((f"b{i}i", f"b{i}o"))
        else:
            g.node(f"n{i}")
            out.append((f"n{i}", f"n{i}"))
    for i in range(n):
        kind = r.choice((PUSH, PULL))
        for j in range(i + 1, n):
            if r.random() < 0.3:
                g.edges.append(Edge(out[i][1], out[j][0], kind))
    return g


@given(st.integers(0, 10**6))
@settings(max_examples=200, deadline=None)
def test_orders_of_random_graphs(seed):
    g = dag(seed)
    try:
        found = phases.order(phases.insert_delays(g))
        g = phases.insert_delays(g)
    except FlowGraphError:
        return
    at = {n: k for k, names in enumerate(found) for n in names}
    assert sorted(at) == sorted(g.names)
    for e in g.edges:
        assert at[e.src] < at[e.dst] if e.kind == BLOCKING else at[e.src] == at[e.dst]
    for names in found:
        o = order.open(g, names)
        assert sorted(o) == sorted(names) and order.close(g, names) == o[::-1] and order.initiators(g, names)
        for e in g.streaming():
            if e.src in names:
                assert (o.index(e.dst) < o.index(e.src)) == (e.kind == PUSH)


FIG = {"A": memory.MemoryAsk(4, 12, 5), "B": memory.MemoryAsk(1, 7, 3), "C": memory.MemoryAsk(8, prio=3), "D": memory.MemoryAsk(7, 12, 7)}


@pytest.mark.parametrize(("budget", "lam", "want"), [(36, 2, (10, 6, 8, 12)), (23, 1, (5, 3, 8, 7)), (20, None, (4, 1, 8, 7)), (60, 29 / 3, (12, 7, 29, 12))])
@pytest.mark.parametrize("method", ["exact", "bisect"])
def test_memory_example(budget, lam, want, method):
    got, each = memory.assign(FIG, budget, method)
    assert lam is None or got == pytest.approx(lam)
    assert tuple(each.values()) == pytest.approx(want)


def test_memory_errors_and_bounds():
    with pytest.raises(memory.MemoryPlanError):
        memory.assign(FIG, 19)
    for bad in (memory.MemoryAsk(5, 4), memory.MemoryAsk(-1), memory.MemoryAsk(prio=0)):
        with pytest.raises(memory.MemoryPlanError):
            memory.assign({"x": bad}, 10)
    assert memory.assign({"x": memory.MemoryAsk(1, 4), "y": memory.MemoryAsk(0, 0)}, 10) == (math.inf, {"x": 4, "y": 0})
    assert memory.equal_split(FIG, 36)["A"] == 9


def test_automatic_split_equals_manual():
    one, two, three = memory.manual_three_phase(1000, 100, 50)
    asks = {"reader": memory.MemoryAsk(100, 100), "a": memory.MemoryAsk(1), "b": memory.MemoryAsk(1)}
    assert memory.assign(asks, 1000)[1]["a"] == two == 450 and (one, three) == (1000, 950)


@given(st.lists(st.tuples(st.integers(0, 50), st.one_of(st.none(), st.integers(0, 100)), st.integers(1, 9)), min_size=1, max_size=8), st.integers(0, 500))
@settings(max_examples=200, deadline=None)
def test_memory_properties(rows, extra):
    asks = {str(i): memory.MemoryAsk(a, math.inf if b is None else a + b, c) for i, (a, b, c) in enumerate(rows)}
    budget = sum(a.lo for a in asks.values()) + extra
    lam, got = memory.assign(asks, budget)
    assert all(asks[n].lo <= v <= asks[n].hi for n, v in got.items()) and sum(got.values()) <= budget + 1e-6
    if lam < math.inf:
        assert sum(got.values()) == pytest.approx(budget)
        assert list(memory.assign(asks, budget, "bisect")[1].values()) == pytest.approx(list(got.values()), abs=1e-6)


def test_priority_ratio():
    got = memory.assign({"a": memory.MemoryAsk(prio=3), "b": memory.MemoryAsk()}, 100)[1]
    assert got == {"a": 75, "b": 25}


def test_traffic_and_time():
    assert cost.external_sort_traffic(10**12, 10**9, 1000) == (1000, 1, 2 * 10**12, 2 * 10**12)
    assert cost.external_sort_traffic(600_000, 1000, 4)[:2] == (600, 5) and cost.external_sort_traffic(5, 10, 4)[1] == 0 and cost.external_sort_traffic(0, 10, 4) == (0, 0, 0, 0)
    assert cost.hours(8e12, 1e8) == pytest.approx(22.22, abs=0.01)
    assert cost.saving((7, 7), (3, 3)) == pytest.approx(float(Fraction(4, 7)))
    assert cost.scan_ios(11, 10) == 2 and cost.sort_ios(5, 100, 10) == 0.5


def test_progress_fraction():
    assert progress.fraction([0.5, 0.3, 0.2], 1, 1, 2) == pytest.approx(0.65)
    assert progress.fraction([0.5, 0.5], 1, 9, 3) == 1 and progress.fraction([1.0], 0, 0, 0) == 1
    assert progress.shares_by_steps([1, 3]) == [0.25, 0.75] and progress.shares_by_steps([0, 0]) == [0.5, 0.5]
    assert "test_plans.py" in progress.identity(1) and "test_progress_fraction" in progress.identity(1)
    assert OUTPUT == "output"


def test_step_traffic_in_items():
    g = regrid_graph()
    items = {n: k for k, n in enumerate(g.names, 1)}
    for mode in ("staged", "fused"):
        assert cost.step_traffic(g, mode, {"rd"}, {"wr"}) == cost.step_traffic(g, mode, {"rd"}, {"wr"}, dict.fromkeys(g.names, 1))
    assert [r[2:] for r in cost.step_traffic(g, "fused", {"rd"}, {"wr"}, items) if sum(r[2:])] == [(0, items["S1i"]), (items["S1o"], 0), (items["rd"], 0), (0, items["S2i"]), (items["S2o"], 0), (0, items["wr"])]
