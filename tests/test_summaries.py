"""The summaries without Spark: worked examples, restrictions, merging, bytes."""

import numpy as np
import pytest

from rankspark import local, synopsis, theory
from rankspark.params import GRID, MethodSpec, fraction
from rankspark.synopsis.dyadic import DyadicDigest, properties
from rankspark.synopsis.gap_tuple import GapSummary, capacity, check_invariants
from rankspark.synopsis.rank_sample import RankSampleSet, Sample
from rankspark.workloads import A, B

STATES = {4: [(0, 1, 0), (4, 2, 0), (7, 1, 0)], 5: [(0, 1, 0), (1, 1, 1), (4, 2, 0), (7, 1, 0)], 8: [(0, 1, 0), (0, 2, 1), (2, 1, 2), (4, 3, 0), (7, 1, 0)], 12: [(0, 1, 0), (0, 2, 1), (1, 1, 3), (2, 2, 2), (4, 4, 0), (7, 2, 0)], 15: [(0, 1, 0), (0, 2, 1), (0, 1, 3), (1, 1, 3), (2, 2, 2), (2, 1, 3), (4, 4, 0), (4, 1, 1), (7, 2, 0)]}
FINAL_B = [(1, 1, 0), (2, 1, 0), (2, 2, 2), (2, 1, 3), (3, 2, 2), (3, 1, 3), (3, 1, 3), (6, 4, 0), (7, 1, 0), (7, 1, 0)]


def traced(data):
    s, states = GapSummary("0.1414", mode="plain", slack="example"), {}
    for i, x in enumerate(data, 1):
        s.absorb_one(x)
        states[i] = s.tuples()
    return s, states


def test_gap_trace_and_answers():
    a, states = traced(A)
    b, _ = traced(B)
    assert {i: states[i] for i in STATES} == STATES and b.tuples() == FINAL_B
    half = [(1, 2)]
    assert a.query(half, pick="first_cover") == [1] and b.query(half, pick="first_cover") == [2]
    assert a.query(half, pick="min_slack", policy="floor") == [2] and b.query(half, pick="min_slack", policy="floor") == [3]
    a._interleave(b)
    assert a.g.sum() == 30 and (a.g + a.delta).max() == 7 <= a.most


def test_capacity_tiles_the_range():
    for p in range(2, 70):
        c = capacity(np.arange(p + 1), p, p)
        assert (c[1:p] > 0).all() and c[p] == 0 and c[0] == c.max() and (np.diff(c[1:]) <= 0).all()


@pytest.mark.parametrize("mode", ["batch", "mixed", "plain", "adaptive"])
@pytest.mark.parametrize("order", ["random", "sorted", "reversed", "equal"])
def test_gap_restrictions(mode, order):
    data = np.random.default_rng(3).integers(0, 5000, 4000)
    data = {"random": data, "sorted": np.sort(data), "reversed": np.sort(data)[::-1], "equal": np.full(4000, 7)}[order]
    parts = local.build_parts(data, MethodSpec.of("gap", "0.02", mode=mode), 5)
    assert all(check_invariants(p, q) for p, q in zip(parts, np.array_split(data, 5), strict=True))
    merged = local.merged(parts, 2)
    assert check_invariants(merged, data)
    assert max(local.rank_errors(data, GRID, merged.query(GRID))) <= 0.02
    assert max(local.rank_errors(data, GRID, merged.query(GRID, pick="min_slack"))) <= 0.04


def test_digest_example_and_properties():
    a, b = DyadicDigest("0.4", 3), DyadicDigest("0.4", 3)
    for d, data in ((a, A), (b, B)):
        d.absorb(np.array(data))
        d.end_chunk()
        assert properties(d) == (True, True)
    assert (a.query([(1, 2)]), b.query([(1, 2)])) == ([2], [3])
    a.merge(b)
    assert a.nodes() == {(0, 0): 5, (0, 1): 2, (0, 2): 7, (0, 3): 7, (2, 1): 4, (0, 6): 1, (0, 7): 2, (3, 0): 2} and a.query([(1, 2)]) == [3]


@pytest.mark.parametrize("method,options", [("digest.batch", {"bits": 20}), ("digest.batch", {"bits": 20, "sweeps": "fixpoint"}), ("digest.online", {})])
def test_digest_error_for_any_number_of_parts(method, options):
    data = np.random.default_rng(5).integers(0, 1 << 20, 20_000)
    for parts in (1, 2, 8, 16):
        m = local.merged(local.build_parts(data, MethodSpec.of(method, "0.01", **options), parts))
        assert max(local.rank_errors(data, GRID, m.query(GRID))) <= 0.01
        if options.get("sweeps"):
            assert properties(m) == (True, True) and len(m) <= theory.digest_bound(m.eps, 20)


def test_digest_is_the_same_in_any_order():
    data = np.random.default_rng(6).integers(0, 1000, 3000)
    one, other = (local.build_parts(x, MethodSpec.of("digest.batch", "0.05", bits=10), 1, 100_000)[0] for x in (data, np.sort(data)))
    assert one.nodes() == other.nodes()


def test_rank_sample_example():
    s = RankSampleSet("0.14142")
    s.samples = [Sample(np.array(v, float), np.arange(5) * 3.0, 1 / 3, 15) for v in ([0, 2, 4, 6, 7], [2, 3, 3, 6, 7])]
    s.n = 30
    assert s.global_rank(np.array([0, 2, 3, 4, 6, 7])).tolist() == [3, 9, 15, 18, 24, 30] and s.query([(1, 2)]) == [3]
    assert theory.sample_rate(30, 2, fraction("0.141421356")) == pytest.approx(1 / 3, rel=1e-6)


def test_randomised_methods_in_the_mean():
    rng = np.random.default_rng(8)
    data = rng.integers(0, 1 << 20, 30_000)
    for method, options in (("rsample", {"total": 30_000, "nodes": 8}), ("levels", {})):
        errors = [np.mean(local.rank_errors(data, GRID, local.run_local(data, MethodSpec.of(method, "0.01", seed=s, **options), 8, GRID))) for s in range(20)]
        assert np.mean(errors) <= 1.5 * 0.01


def test_rank_sample_is_unbiased():
    data, seen = np.arange(20_000), []
    for seed in range(60):
        m = local.merged(local.build_parts(np.random.default_rng(1).permutation(data), MethodSpec.of("rsample", "0.02", total=20_000, nodes=4, seed=seed), 4))
        seen.append(float(m.global_rank(np.array([9_999]))[0]))
    p = theory.sample_rate(20_000, 4, fraction("0.02"))
    assert abs(np.mean(seen) - 10_000) <= 4 * (theory.rank_variance(4, p) / 60) ** 0.5 + 4 / p / 10 and np.var(seen) <= 1.5 * theory.rank_variance(4, p)


def test_levels_weight_and_lossless():
    data = np.random.default_rng(2).permutation(5000)
    m = local.merged(local.build_parts(data, MethodSpec.of("levels", "0.0001"), 4))
    assert m.weighted()[1].sum() == 5000 and max(local.rank_errors(data, GRID, m.query(GRID))) == 0
    wide = local.merged(local.build_parts(np.arange(200_000), MethodSpec.of("levels", "0.05"), 4))
    assert 0.7 < wide.weighted()[1].sum() / 200_000 < 1.3 and len(wide) <= wide.most * wide.size * 2


@pytest.mark.parametrize("method,options", [("gap", {}), ("rsample", {}), ("digest.batch", {"bits": 10}), ("digest.online", {}), ("levels", {})])
def test_bytes_empty_and_tiny(method, options):
    spec = MethodSpec.of(method, "0.1", **options)
    for data in ([], [5], [5, 5], [1, 9]):
        parts = local.build_parts(np.array(data, dtype=np.int64), spec, 3)
        m = local.merged([synopsis.unpack(p.pack()) for p in parts])
        got = m.query([(1, 2)])
        assert got == [None] if not data else got[0] is None or got[0] in data


def test_a_broken_summary_is_noticed():
    data = np.random.default_rng(4).integers(0, 1 << 20, 20_000)
    m = local.merged(local.build_parts(data, MethodSpec.of("gap", "0.01"), 4))
    assert len(m) < len(data) / 10
    m.g = m.g[::-1].copy()
    m.g[0] += 5000
    m.n += 5000
    assert max(local.rank_errors(data, GRID, m.query(GRID))) > 0.01


def test_batch_digest_bounds_its_memory(monkeypatch):
    """Many batches add up as one does; past the bound of nodes the early folds keep the error below eps."""
    data = np.random.default_rng(3).integers(0, 1 << 16, 120_000)
    whole = synopsis.DyadicDigest("0.01", bits=16)
    whole.absorb(data)
    monkeypatch.setattr(synopsis.DyadicDigest, "MOST_PENDING", 5_000)
    parts = synopsis.DyadicDigest("0.01", bits=16)
    for at in range(0, len(data), 1_000):
        parts.absorb(data[at : at + 1_000])
        assert parts._waiting <= max(5_000, len(parts.index)) and sum(len(v) for v, _ in parts._pending) == parts._waiting
    for d in (whole, parts):
        d.local_finalize()
    assert parts.nodes() == whole.nodes()
    monkeypatch.setattr(synopsis.DyadicDigest, "MOST_NODES", 8_000)
    small = synopsis.DyadicDigest("0.01", bits=16)
    for at in range(0, len(data), 1_000):
        small.absorb(data[at : at + 1_000])
        assert len(small.index) <= 16_000
    small.local_finalize()
    ordered = np.sort(data)
    for (a, b), v in zip(GRID, small.query(GRID), strict=True):
        low, high = np.searchsorted(ordered, v, "left"), np.searchsorted(ordered, v, "right")
        assert low - 0.01 * len(data) <= a * len(data) // b <= high + 0.01 * len(data)


def test_rank_sample_with_estimated_ranks_holds_only_its_sample():
    data = np.random.default_rng(4).integers(0, 1 << 20, 400_000)
    s = synopsis.RankSampleSet("0.01", total=len(data), nodes=4, rank_mode="estimated")
    for at in range(0, len(data), 10_000):
        s.absorb(data[at : at + 10_000])
    held = sum(len(v) for v in s._values)
    assert held < 1_000 and s.n == len(data)
    s.local_finalize()
    (own,) = s.samples
    assert own.size == len(data) and len(own.values) == held and (np.diff(own.values) >= 0).all()
    ordered = np.sort(data)
    off = [abs(np.searchsorted(ordered, v) - a * len(data) // b) for (a, b), v in zip(GRID, s.query(GRID), strict=True)]
    assert np.mean(off) < 0.12 * len(data)  # a sample of about 200: sqrt(200) ranks of 2,000 values each


@pytest.mark.parametrize("eps", ["0.1", "0.01", "0.001"])
def test_mixed_insertion_in_batches_is_that_item_by_item(eps, monkeypatch):
    data = np.random.default_rng(6).integers(0, 1 << 20, 9000)
    orders = {"random": data, "sorted": np.sort(data), "reversed": np.sort(data)[::-1], "few": data % 7, "walk": np.cumsum(data % 100 - 40), "floats": data / 3}
    alone = {}
    for name, x in orders.items():
        alone[name] = GapSummary(eps, mode="mixed")
        for v in x.tolist():
            alone[name].absorb_one(v)
    calls, one = [], GapSummary.absorb_one
    monkeypatch.setattr(GapSummary, "absorb_one", lambda self, v: (calls.append(v), one(self, v)))
    for name, x in orders.items():
        s = GapSummary(eps, mode="mixed")
        for at in range(0, len(x), 2000):
            s.absorb(x[at : at + 2000])
        assert s.n == alone[name].n and s.tuples() == alone[name].tuples(), name
    assert len(calls) <= 64 * len(orders)


@pytest.mark.parametrize("eps", ["0.1", "0.001"])
def test_online_digest_sinks_batches(eps, monkeypatch):
    from rankspark.synopsis.dyadic import OnlineDigest

    opened, open_ = [], OnlineDigest._open
    monkeypatch.setattr(OnlineDigest, "_open", lambda self: (opened.append(1), open_(self))[1])
    data = np.random.default_rng(7).integers(0, 1 << 20, 120_000)
    for x in (data, np.sort(data), data % 50):
        s = OnlineDigest(eps)
        for at in range(0, len(x), 5000):
            s.absorb(x[at : at + 5000])
        s.end_chunk()
        assert s.n == len(x) == s.count.sum() and properties(s)[0]
        assert max(local.rank_errors(x, GRID, s.query(GRID))) <= float(eps)
    assert len(opened) <= 3 * 20_000


@pytest.mark.parametrize("eps", ["0.05", "0.01", "0.001"])
def test_mixed_insertion_of_increasing_items_cuts_runs_by_number(eps):
    import sys

    rng, steps = np.random.default_rng(7), [0]
    data = np.sort(rng.integers(0, 1 << 20, 40_000))
    whole, single = GapSummary(eps, mode="mixed"), GapSummary(eps, mode="mixed")
    for v in data.tolist():
        single.absorb_one(v)

    def count(frame, event, arg):
        steps[0] += event == "line"
        return count if frame.f_code.co_name in ("absorb", "_absorb_mixed", "_append_run") else None

    sys.settrace(count)
    whole.absorb(data)
    sys.settrace(None)
    assert whole.pack() == single.pack() and check_invariants(whole, data)
    assert steps[0] < 3 * len(data)  # lines run; cutting them item by item takes eight for each


@pytest.mark.parametrize(("eps", "power"), [("0.05", 1), ("0.001", 1), ("0.0005", 3)])
def test_online_digest_keeps_counters_in_arrays(eps, power, monkeypatch):
    from rankspark.synopsis.dyadic import OnlineDigest

    rng = np.random.default_rng(3)
    data = (rng.random(700_000) ** power * (1 << 18)).astype(np.int64)
    arrays, sparse = OnlineDigest(eps), OnlineDigest(eps)
    sparse.DENSE_BITS = 0
    seen = set()
    for at in range(0, len(data), 131_072):
        for d in (arrays, sparse):
            d.absorb(data[at : at + 131_072])
        seen.add(arrays._dense is not None)
    assert True in seen and sparse._dense is None
    assert arrays.nodes() == sparse.nodes() and arrays.count.sum() == len(data) and properties(arrays)[0]
    merged = synopsis.unpack(arrays.pack())
    merged.merge(synopsis.unpack(sparse.pack()))
    assert merged.n == 2 * len(data) == merged.count.sum()
