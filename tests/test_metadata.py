"""Catalog, graph, planning, routing, tuning, scheduling: no Spark jobs."""

import threading
import time

import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from widefeat.catalog import Catalog
from widefeat.metastore import MetaStore
from widefeat.model import ABSENT, COMPUTED, BatchEntry, Column, ConflictError, FeatureSpec, Output, Physical, PlanningError
from widefeat.operators.executor import Scheduler, TaskResult
from widefeat.operators.governance import access_frequency, assign_shards, compaction_due, split_ranges, tier
from widefeat.plans import tuning
from widefeat.plans.dag import FeatureGraph
from widefeat.plans.planner import FusedTask, minimum_closure, plan_tasks, span_batches
from widefeat.plans.routing import ClusterLoad, OperatorProfile, choose_lane


def spec(name, *inputs, **options):
    return FeatureSpec.sql(name, "bigint", "1", inputs, **options)


@pytest.fixture
def catalog():
    c = Catalog()
    c.create_table("t", [Column("raw", "string")])
    c.register_batches("t", [(BatchEntry(b, 3), [Physical(f"p{b}", "core", f"/x/{b}", b, ("raw",), rows=3)], ["raw"], []) for b in ("a", "b")])
    for s in (spec("plain", "raw"), spec("lang", "plain"), spec("length", "plain"), spec("quality", "plain", "lang"), FeatureSpec("m", ("plain", "quality"), (Output("math", "bigint"),), ("plain",), fn="math_hit", mode="all", model_mb=100)):
        c.add_feature("t", s)
    return c


def test_registration_errors(catalog):
    for bad in (spec("x", "nothing"), spec("lang", "plain"), FeatureSpec("y", ("plain",), (Output("length", "bigint"),), ("1",))):
        with pytest.raises(PlanningError):
            catalog.add_feature("t", bad)
    with pytest.raises(PlanningError):
        catalog.add_feature("t", spec("plain", "quality"), bump=True)
    assert catalog.add_feature("t", spec("length", "raw"), bump=True).version == 2


def test_worked_example(catalog):
    snap = catalog.snapshot("t")
    work = minimum_closure(snap.graph, snap.status, [("a", "math")])
    assert work == {("a", c) for c in ("plain", "lang", "quality", "math")}
    catalog.set_status("t", [("a", "plain"), ("a", "lang")], COMPUTED)
    snap = catalog.snapshot("t")
    assert minimum_closure(snap.graph, snap.status, [("a", "math")]) == {("a", "quality"), ("a", "math")}
    assert minimum_closure(snap.graph, snap.status, [("a", "lang")]) == set()
    assert minimum_closure(snap.graph, snap.status, [("a", "lang")], recompute=True) == {("a", "lang")}
    catalog.set_status("t", [("b", "raw")], ABSENT)
    with pytest.raises(PlanningError):
        minimum_closure(snap.graph, catalog.snapshot("t").status, [("b", "length")])


@pytest.mark.parametrize("fuse,tasks", [("off", 5), ("inputs", 4), ("physical", 4), ("chain", 2)])
def test_fusion_modes(catalog, fuse, tasks):
    snap = catalog.snapshot("t")
    work = minimum_closure(snap.graph, snap.status, [("a", "math"), ("a", "length")])
    plan = plan_tasks(snap, work, fuse)
    assert len(plan) == tasks
    done = set()
    for t in plan:
        assert set(t.after) <= done and len(t.batches) == 1
        done.add(t.number)
    both = plan_tasks(snap, minimum_closure(snap.graph, snap.status, [(b, c) for b in "ab" for c in ("math", "length")]), fuse)
    assert len(span_batches(both)) == tasks and all(len(t.batches) == 2 for t in span_batches(both))


graphs = st.integers(2, 9).flatmap(lambda n: st.lists(st.tuples(st.integers(0, n - 1), st.integers(0, n - 1)), max_size=20).map(lambda es: (n, {(max(a, b), min(a, b)) for a, b in es if a != b})))


@settings(max_examples=60, deadline=None)
@given(graphs, st.data())
def test_closure_properties(graph, data):
    n, edges = graph
    inputs = {f"c{i}": [f"c{b}" for a, b in edges if a == i] for i in range(n)}
    g = FeatureGraph.from_specs(spec(c, *p) for c, p in inputs.items() if p)
    status = {("b", c): COMPUTED for c in inputs if c not in g.producers or data.draw(st.booleans())}
    targets = [("b", c) for c in data.draw(st.lists(st.sampled_from(sorted(inputs)), max_size=4))]
    got = minimum_closure(g, status, targets)
    want = {("b", k) for _, c in targets for k in {c, *g.ancestors(c)} if status.get(("b", k)) != COMPUTED}
    assert got == want and got == minimum_closure(g, status, sorted(got) + targets)
    grown = set(targets)  # the walk that adds while it goes gives the same set
    todo = list(targets)
    while todo:
        b, c = todo.pop()
        for k in g.ancestors(c):
            if status.get((b, k)) != COMPUTED and (b, k) not in grown:
                grown.add((b, k))
                todo.append((b, k))
    assert {p for p in grown if status.get(p) != COMPUTED} == got
    level = {c: i for i, cs in enumerate(g.levels(c for _, c in got)) for c in cs}
    assert all(level[a] < level[c] for c in level for a in g.ancestors(c) if a in level)


def test_cycle():
    with pytest.raises(PlanningError):
        FeatureGraph.from_specs([spec("a", "b"), spec("b", "a")]).check_acyclic()


def test_optimistic_locking_and_snapshots(catalog):
    v = catalog.snapshot("t").version
    old = catalog.snapshot("t")
    catalog.swap_mapping("t", ["pa"], [Physical("pa2", "core", "/y", "a", ("raw",))], expected=v)
    with pytest.raises(ConflictError):
        catalog.swap_mapping("t", ["pb"], [], expected=v)
    assert [p.phys_id for p in old.resolve("a", "raw")] == ["pa"] and [p.phys_id for p in catalog.snapshot("t").resolve("a", "raw")] == ["pa2"]
    assert [p.phys_id for p in catalog.snapshot("t", version=v).resolve("a", "raw")] == ["pa"]
    assert [p.path for p in catalog.dropped_physical("t")] == ["/x/a"]
    with pytest.raises(PlanningError):
        catalog.register_batches("t", [(BatchEntry("a", 1), [], [], [])])
    assert catalog.changes_since("t", v)[0][1] == "layout"


def test_one_of_two_writers_wins(tmp_path):
    stores = [Catalog(MetaStore(str(tmp_path / "m.db"))) for _ in range(2)]
    stores[0].create_table("t", [Column("raw", "string")])
    v, wins = stores[0].snapshot("t").version, []

    def write(c, i):
        try:
            c.register_batches("t", [(BatchEntry(f"b{i}", 1), [], ["raw"], [])], expected=v)
            wins.append(i)
        except ConflictError:
            pass

    threads = [threading.Thread(target=write, args=(c, i)) for i, c in enumerate(stores)]
    [t.start() for t in threads]
    [t.join() for t in threads]
    assert len(wins) == 1 and len(stores[0].snapshot("t").batches) == 1


def test_locks_and_leases(catalog):
    s = catalog.store
    assert s.try_lock("t", "core", "me") and s.try_lock("t", "core", "me") and not s.try_lock("t", "core", "you")
    s.unlock("t", "core", "you")
    assert not s.try_lock("t", "core", "you")
    s.unlock("t", "core", "me")
    assert s.try_lock("t", "core", "you", lease_s=-1) and s.try_lock("t", "core", "me")


def tasks_of(*edges):
    after = {}
    for a, b in edges:
        after.setdefault(a, set())
        if b is not None:
            after.setdefault(b, set())
            after[a].add(b)
    return [FusedTask(n, ("b",), "sql", 0, (), (f"c{n}",), tuple(sorted(ps))) for n, ps in sorted(after.items())]


def test_scheduler_order_retries_and_blocking():
    tasks, done, tries, lock = tasks_of((1, 0), (2, 1), (3, 0), (4, None)), [], {}, threading.Lock()

    def work(t, attempt):
        with lock:
            tries[t.number] = attempt
        if t.number == 1 or (t.number == 4 and attempt < 3):
            raise ValueError("bad")
        with lock:
            assert set(t.after) <= set(done)
            done.append(t.number)
        return TaskResult(t, True, attempt)

    results, failed, blocked = Scheduler(3, 2).run(tasks, work)
    assert sorted(done) == [0, 3, 4] and failed == {1} and blocked == {2} and tries == {0: 1, 1: 3, 3: 1, 4: 3}
    assert sum(not r.ok for r in results) == 1


def test_scheduler_concurrency():
    running, most, lock = [0], [0], threading.Lock()

    def work(t, attempt):
        with lock:
            running[0] += 1
            most[0] = max(most[0], running[0])
        time.sleep(0.02)
        with lock:
            running[0] -= 1
        return TaskResult(t, True, attempt)

    Scheduler(2, 0).run(tasks_of(*((i, None) for i in range(8))), work)
    assert most[0] == 2


def test_routing():
    small, large, none = OperatorProfile(True, 350, False), OperatorProfile(True, 7000, False), OperatorProfile(False, 0, True)
    assert choose_lane("cpu_only", large, ClusterLoad(1, 0)) == "arrow" and choose_lane("gpu_only", none, ClusterLoad(0, 1)) == "gpu"
    assert [choose_lane("all", p, ClusterLoad(0.2, 0.2)) for p in (none, small, large)] == ["sql", "arrow", "gpu"]
    assert choose_lane("all", small, ClusterLoad(0.95, 0.1)) == "gpu" and choose_lane("all", large, ClusterLoad(0.1, None)) == "arrow"


def test_tuning():
    small, large = tuning.InputStats(10, 10**6, 10**9), tuning.InputStats(10, 10**6, 10**12)
    a, b = tuning.cold_start(small, 350), tuning.cold_start(large, 350)
    assert a.split_mb >= b.split_mb and a.batch_rows >= b.batch_rows and b.parallelism > a.parallelism
    h = tuning.History()
    assert tuning.adapt("f", small, 0, h).source == "rules"
    h.record(tuning.Run("f", 10**9, 1, 1, 1000))
    h.record(tuning.Run("f", 4 * 10**9, 1, 1, 2000))
    assert tuning.adapt("f", small, 0, h).worker_mb == pytest.approx(1100)
    assert h.interpolate("f", 2 * 10**9, "peak_mb") == pytest.approx(2**0.5 * 1000)
    assert h.interpolate("f", 10**12, "peak_mb") is None
    h.record(tuning.Run("f", 10**9, 1, 1, 3000, ok=False))
    assert tuning.adapt("f", small, 0, h).worker_mb == 4500


def test_governance_rules():
    assert [compaction_due(n, s) for n, s in ((1000, 0), (1001, 0), (100, 50), (100, 51), (0, 0))] == [False, True, False, True, False]
    day = 86400
    assert [tier(0, 3 * day), tier(0, 8 * day), tier(0, 8 * day, last_deep_s=5 * day), tier(3 * day, 3.5 * day, last_light_s=3 * day)] == ["light", "deep", None, None]
    ranges = split_ranges(10, 10, max_rows=3)
    assert ranges[0][0] == 0 and ranges[-1][1] == 1 << 32 and len(ranges) == 4 and all(a[1] == b[0] for a, b in zip(ranges, ranges[1:]))
    shards = assign_shards(["k", *(f"c{i}" for i in range(30))], ["k"], {"c7": 5.0}, limit=20, headroom=0.9, max_shard=8)
    assert shards[0][:2] == ["k", "c7"] and all(len(s) <= 8 for s in shards) and sorted(sum(shards, [])) == sorted(["k", *(f"c{i}" for i in range(30))])
    assert access_frequency([(0, ["a"]), (30 * day, ["a", "b"])], 30 * day) == {"a": 1.5, "b": 1.0}
