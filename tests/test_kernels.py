"""Golden traces on eight one-dimensional nodes, limiting cases and invariants of the kernels."""

import numpy as np
import pytest

from thriftvec.operators import kernels as kn

EXACT = np.array([0, 3, 1, 5, 2, 8, 7, 6], float)[:, None]
COARSE = np.array([0, 4, 0, 4, 4, 8, 8, 4], float)
NBRS = [[1, 2, 4], [0, 3, 4], [0, 4], [1, 5, 7], [0, 1, 2], [3, 6], [5, 7], [3, 6]]
Q = np.array([6.4])


def run(alpha, ef, **more):
    g = kn.Shard.build(np.arange(8), [np.array(a) for a in NBRS])
    calls = []

    def fetch(at):
        calls.append(sorted(at.tolist()))
        return EXACT[at]

    res, t = kn.traverse(g, Q, 0, 2, ef, fetch, alpha=alpha, cheap=lambda at: (COARSE[at] - 6.4) ** 2, **more)
    return [(round(d**0.5, 6), i) for d, i in res], [s[1] for s in t.steps], calls, t


@pytest.mark.parametrize("ef", [2, 3])
def test_full_share_equals_recompute_all(ef):
    res, order, calls, t = run(1.0, ef)
    assert res == [(0.4, 7), (0.6, 6)] and order == [0, 1, 3, 7, 6] and t.exact == 8
    assert calls == [[0], [1, 2, 4], [3], [5, 7], [6]]
    assert run(None, ef)[0] == res


@pytest.mark.parametrize("ef", [2, 3])
def test_half_share(ef):
    res, order, calls, t = run(0.5, ef)
    assert res == [(0.6, 6), (1.4, 3)] and order == [0, 1, 3, 5, 6] and t.exact == 6
    assert calls == [[0], [1, 4], [3], [5], [6]]


def test_batching_loses_nothing():
    assert run(1.0, 8, batch_target=100)[0] == [(0.4, 7), (0.6, 6)]
    assert run(1.0, 8, batch_target=1)[3].batches == [1] * 8


def test_bad_arguments():
    for a, ef in ((0.0, 3), (1.5, 3), (0.5, 1)):
        with pytest.raises(ValueError):
            run(a, ef)


def test_empty_and_single():
    g = kn.Shard.build(np.empty(0, np.int64), [])
    assert kn.traverse(g, Q, g.hub(), 2, 3, lambda at: EXACT[at])[0] == []
    g = kn.Shard.build(np.array([5]), [np.array([], int)])
    assert kn.traverse(g, Q, 0, 2, 3, lambda at: EXACT[at])[0] == [(pytest.approx(6.4**2), 5)]


@pytest.fixture(scope="module")
def cloud():
    r = np.random.default_rng(3)
    return np.arange(200), r.normal(size=(200, 8))


@pytest.mark.parametrize("rule", ["closest", "diverse", "relaxed"])
def test_layered_build(cloud, rule):
    ids, x = cloud
    b = kn.layered_build(ids, x, cap=12, ef=60, rule=rule)
    assert max(len(a) for a in b.layers[0]) <= 12
    g = kn.Shard.build(ids, [np.array(sorted(a)) for a in b.layers[0]])
    hits = 0
    for q in x[:40] + 0.01:
        true = set(np.argsort(((x - q) ** 2).sum(1))[:5])
        hits += len(true & {i for _, i in kn.traverse(g, q, g.hub(), 5, 60, lambda at: x[at])[0]})
    assert hits >= 0.85 * 200


@pytest.mark.parametrize("how", ["original", "incremental"])
def test_hub_rebuild_caps(cloud, how):
    ids, x = cloud
    lists = [sorted(a) for a in kn.layered_build(ids, x, cap=20, ef=60).layers[0]]
    out = kn.hub_rebuild(ids, x, lists, cap=20, low=4, beta=0.05, ef=40, candidates=how)
    assert max(len(a) for a in out) <= 20
    assert sum(map(len, out)) < sum(map(len, lists))


def test_insert_costs_fall(cloud):
    ids, x = cloud
    links = kn.layered_build(ids[:180], x[:180], cap=10, ef=40).layers[0]
    lists = [sorted(a, key=a.get) for a in links]
    cost = []
    for mode in ("naive", "cached", "light", "simple"):
        cost.append(0)
        for u in range(180, 200):  # each from the same graph, so that the counts compare
            ls, asked = [list(a) for a in lists] + [[] for _ in range(20)], []

            def encode(nodes, asked=asked):
                asked.extend(nodes)
                return x[nodes]

            led = kn.insert(ls, u, x[u], encode, 0, 10, 40, mode, np.round(x, 1) if mode in ("light", "simple") else None)
            assert led.encodes == len(asked) and u not in asked
            assert mode == "naive" or len(set(asked)) == len(asked)
            cost[-1] += led.encodes
            assert max(len(a) for a in ls) <= 10 and ls[u]
    assert cost[0] > cost[1] >= cost[2] >= cost[3]


def test_full_queue_is_visited_in_rounds_by_all_queries_together(cloud, monkeypatch):
    """A queue of all nodes gives what the step-by-step traversal gives, fetches each vector once and keeps no O(n) scan."""
    import pyarrow as pa

    from thriftvec.functions.encoders import Encoder
    from thriftvec.operators import search as se
    from thriftvec.plans.planner import SearchSpec

    ids, x = cloud
    lists = [sorted(a) for a in kn.layered_build(ids, x, cap=12, ef=60).layers[0]]
    nodes = pa.table({"node_id": ids, "nbrs": lists, "code": pa.nulls(len(ids), pa.binary()), "text": [",".join(map(str, v)) for v in x]})
    asked, plain = [], Encoder.encode
    monkeypatch.setattr(Encoder, "encode", lambda self, texts: asked.append(len(texts)) or plain(self, texts))
    qs = pa.table({"query_id": [1, 2, 3], "qv": [list(v) for v in x[:3] + 0.01]})
    for target in (None, 64, 1):
        asked.clear()
        spec = SearchSpec(k=5, ef=200, mode="recompute", batch_target=target)
        out = se.run_queries(nodes, qs, spec, Encoder("lookup", 8), None, None, False).to_pylist()
        once = sum(asked)
        assert max(asked) <= (target or 200)
        slow = se.run_queries(nodes, qs, spec, Encoder("lookup", 8), None, None, True).to_pylist()
        key = lambda rows: [(r["query_id"], r["node_id"], r["dist"]) for r in rows if r["kind"] == "r"]
        count = lambda rows: [(r["step"], r["a"], r["c"]) for r in rows if r["kind"] == "s"]
        assert key(out) == key(slow) and count(out) == count(slow) == [(once, once, once)] * 3


def test_queue_keeps_the_nearest_to_visit():
    r = np.random.default_rng(5)
    q = kn.Bounded(7)
    for i, d in enumerate(r.random(60).tolist()):
        q.offer(d, i, i)
        if i % 3 == 0:
            want = next((x for x in q.rows if x[2] not in q.visited), None)
            assert q.next() == want
            if want:
                q.visited.add(want[2])
    left = [x for x in q.rows if x[2] not in q.visited]
    assert q.take(3) == left[:3] and q.take(9) == left[3:] and q.next() is None


def test_every_node_leads_to_every_other():
    from thriftvec.operators.baselines import connect

    x = np.arange(12.0).reshape(6, 2)
    links = [{1: 1.0}, {}, {1: 1.0}, {4: 1.0}, {3: 1.0}, {}]
    connect(links, x, 0)
    off = np.cumsum([0, *map(len, links)])
    nb = np.array([v for a in links for v in a])
    assert all(sum(map(len, kn.waves(off, nb, u))) == 6 for u in range(6))


def test_distances_taken_at_once_change_no_links(cloud, monkeypatch):
    ids, x = cloud[:2]
    for rule in ("closest", "diverse", "relaxed"):
        monkeypatch.setattr(kn, "ALL_PAIRS", 0)
        want = [sorted(a) for a in kn.layered_build(ids, x, cap=8, ef=40, rule=rule).layers[0]]
        monkeypatch.setattr(kn, "ALL_PAIRS", len(ids) ** 2)
        assert [sorted(a) for a in kn.layered_build(ids, x, cap=8, ef=40, rule=rule).layers[0]] == want
    d = kn.all_distances(x.astype(float), x[:70].astype(float), rows=32)
    assert d == pytest.approx(((x[None, :].astype(float) - x[:70, None]) ** 2).sum(2), abs=1e-9)
