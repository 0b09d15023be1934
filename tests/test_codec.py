"""Invariants of the in-memory form, by property tests against plain arrays."""

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from splitcount.operators import bits
from splitcount.operators.codec import CodedTrace, Sketch, Trace, best_base_scan, decoded_registers, lazy_base, merge
from splitcount.operators.deep import EliasFano, deep_size

registers = st.integers(4, 7).flatmap(lambda p: st.lists(st.one_of(st.integers(0, 12), st.integers(0, 63)), min_size=1 << p, max_size=1 << p))
same_size = st.integers(4, 6).flatmap(lambda p: st.lists(st.lists(st.integers(0, 63), min_size=1 << p, max_size=1 << p), min_size=3, max_size=3))
stream = st.lists(st.tuples(st.integers(0, 15), st.integers(1, 40)), max_size=200)


@given(st.integers(1, 24), st.lists(st.integers(0, 2**24 - 1), max_size=100))
def test_packing_round_trip(width, values):
    v = np.array([x & (1 << width) - 1 for x in values], np.uint64)
    data = bits.pack(v, width)
    assert len(data) == -(-len(v) * width // 64) * 8
    assert bits.unpack(data, width, len(v)).tolist() == v.tolist()


@given(st.integers(1, 56), st.data())
@settings(max_examples=80, deadline=None)
def test_packed_arrays_change_in_place(width, data):
    """Sets, ordered insertions, deletions and searches against a plain list."""
    a, want = bits.PackedArray(width), []
    for v in data.draw(st.lists(st.integers(0, (1 << width) - 1), max_size=60)):
        at = a.find(v)
        assert at == sum(x < v for x in want)
        if at < len(want) and want[at] == v and data.draw(st.booleans()):
            a.delete(at)
            del want[at]
        else:
            a.insert(at, v)
            want.insert(at, v)
        assert a.values().tolist() == want and len(a.to_bytes()) == -(-len(want) * width // 64) * 8
    for k in range(0, len(want), 3):
        a[k] = want[k] = want[k] ^ 1
    assert [a[k] for k in range(len(want))] == want and a.values(len(want) // 2).tolist() == want[len(want) // 2 :]
    assert a.to_bytes() == bits.pack(np.array(want, np.uint64), width)


@given(registers, st.integers(1, 6))
@settings(max_examples=60, deadline=None)
def test_round_trip_and_lookup(regs, kappa):
    s = Sketch.from_registers(np.array(regs), kappa)
    assert s.to_registers().tolist() == regs
    assert [s.get(j) for j in range(len(regs))] == regs
    assert [r for _, r in s.iter_registers()] == regs
    back = Sketch.from_bytes(s.to_bytes())
    assert back.to_registers().tolist() == regs and back.to_bytes() == s.to_bytes()


@given(registers, st.integers(1, 6))
@settings(max_examples=60, deadline=None)
def test_base_is_optimal(regs, kappa):
    sparse = [sum(not b <= r < b + (1 << kappa) for r in regs) for b in range(64)]
    got = best_base_scan(np.bincount(regs, minlength=64), kappa)
    assert got.sparse == min(sparse)
    assert got.base == min(b for b in set(regs) if sparse[b] == min(sparse))


@given(same_size)
@settings(max_examples=40, deadline=None)
def test_merge_laws(three):
    a, b, c = (Sketch.from_registers(np.array(x)) for x in three)
    want = Sketch.from_registers(np.max(np.array(three), axis=0)).to_bytes()
    assert merge([a, b, c]).to_bytes() == want
    assert merge([merge([a, b]), c]).to_bytes() == want == merge([c, merge([b, a])]).to_bytes()
    assert merge([a, a]).to_bytes() == a.to_bytes() == merge([a, Sketch.empty(a.p)]).to_bytes()


@given(stream)
@settings(max_examples=60, deadline=None)
def test_traces_agree_with_registers(pairs):
    want = [0] * 16
    for j, r in pairs:
        want[j] = max(want[j], r)
    made = {}
    for variant in ("opt", "lazy", "min"):
        for reject in (True, False):
            t = Trace(4, variant=variant, early_reject=reject)
            for j, r in pairs:
                t.offer(j, r)
            assert t.regs == want
            made[variant, reject] = t
            assert t.sketch().bits == t.bits and t.state.to_bytes() == Sketch.from_registers(np.array(want), base=t.base, variant=variant).to_bytes()
            assert t.low == min(want) and Sketch.from_bytes(t.state.to_bytes()).to_registers().tolist() == want
        assert made[variant, True].base == made[variant, False].base  # rejecting early changes nothing
    best = Sketch.from_registers(np.array(want))
    assert made["opt", True].bits == best.bits <= min(made["lazy", True].bits, made["min", True].bits)
    assert made["opt", True].counters.compress_calls == made["opt", True].counters.changed
    pruned, full = made["opt", True], Trace(4, variant="opt", prune=False)
    for j, r in pairs:
        full.offer(j, r)
    assert full.bits == pruned.bits and full.counters.candidates >= pruned.counters.candidates


@given(stream)
@settings(max_examples=25, deadline=None)
def test_coded_registers(pairs):
    t, want = CodedTrace(4), [0] * 16
    for j, r in pairs:
        t.offer(j, r)
        want[j] = max(want[j], r)
    assert decoded_registers(t.data, 4).tolist() == want
    assert t.decodes <= len(pairs)


@given(stream)
@settings(max_examples=40, deadline=None)
def test_many_at_once(pairs):
    j, r = [x[0] for x in pairs], [x[1] for x in pairs]
    one, n = Sketch.empty(4).offer_many(j, r)
    assert one.to_bytes() == Sketch.from_pairs(4, j, r).to_bytes()
    assert one.offer_many(j, r) == (one, 0) or not pairs


@given(same_size, st.sampled_from(["opt", "lazy", "min"]), st.integers(1, 6))
@settings(max_examples=60, deadline=None)
def test_variants_keep_their_rule_in_blobs(three, variant, kappa):
    """Batches and merges hold the same registers under every variant; the lazy base climbs only while that helps."""
    a, b, c = (Sketch.from_registers(np.array(x), kappa, variant=variant) for x in three)
    want = np.max(np.array(three), axis=0)
    assert Sketch.from_bytes(a.to_bytes()).variant == variant
    for got in (merge([a, b, c]), a.offer_many(np.arange(len(want)), want)[0]):
        assert got.variant == variant and got.to_registers().tolist() == want.tolist()
    best = Sketch.from_registers(want, kappa).bits
    assert merge([a, b, c]).bits == best or variant == "min"
    hist = np.bincount(want, minlength=65)
    at = lazy_base(hist, kappa, 0)
    inside = lambda x: int(hist[x : x + (1 << kappa)].sum())
    later = [x for x in np.flatnonzero(hist).tolist() if x > at]
    assert inside(at) >= inside(0) and (not later or inside(later[0]) <= inside(at))


def test_blocks_meet_across_their_borders():
    rng = np.random.default_rng(6)
    regs = [np.minimum(rng.geometric(0.5, 1 << 14) + x, 63) for x in (0, 6)]
    s = [Sketch.from_registers(x) for x in regs]
    assert all(np.array_equal(x.to_registers(), y) for x, y in zip(s, regs, strict=True))
    assert merge(s).to_bytes() == Sketch.from_registers(np.maximum(*regs)).to_bytes()
    assert [s[1].get(j) for j in range(4090, 4102)] == regs[1][4090:4102].tolist()


@given(st.lists(st.integers(0, 4095), unique=True, max_size=200))
def test_elias_fano(values):
    v = np.sort(np.array(values, np.int64))
    assert EliasFano.of(v, 4096).values().tolist() == v.tolist()


def test_deep_reports_a_size():
    rng = np.random.default_rng(1)
    regs = np.minimum(rng.geometric(0.5, 1 << 12) + 8, 63)
    got = deep_size(Sketch.from_registers(regs))
    assert got["kappa"] in (2, 3) and 0 < got["bits"] <= got["plain_sparse_bits"]


def test_merge_refuses_other_kinds():
    with pytest.raises(ValueError):
        merge([Sketch.empty(4), Sketch.empty(5)])
    with pytest.raises(ValueError):
        merge([Sketch.empty(4), Sketch.empty(4, seed=1)])


def test_fold_equals_direct():
    rng = np.random.default_rng(2)
    j, r = rng.integers(0, 1 << 8, 2000), rng.geometric(0.5, 2000)
    assert Sketch.from_pairs(8, j, r).fold(6).to_bytes() == Sketch.from_pairs(6, j >> 2, r).to_bytes()
