"""Hashes, word tests, tables and baselines without Spark."""

from dataclasses import replace

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from fpfilter.functions import lanes
from fpfilter.functions.hashing import MASK, factor, linear_int, linear_np, mix_int, mix_np
from fpfilter.operators import baselines, cuckoo
from fpfilter.operators.spec import ALL_VARIANTS, VARIANTS, sized, threshold, variant
from fpfilter.plans import models

KEYS = mix_np(np.arange(4000))
OTHERS = mix_np(np.arange(4000, 24000))


@given(st.integers(0, MASK), st.sampled_from([1, 2, 3, 6, 1 << 20, 16007, (1 << 31) - 1, (1 << 60) - 1]))
@settings(max_examples=200, deadline=None)
def test_numpy_hash_is_the_integer_hash(x, b):
    a = factor(3, "address")
    assert linear_np(np.array([x], np.uint64), a, b)[0] == linear_int(x, a, b) < b
    assert int(mix_np(np.array([x], np.uint64))[0]) == mix_int(x)


def test_factors_are_odd_and_differ_by_role_and_seed():
    found = {factor(s, r) for s in range(5) for r in ("sub", "address", "fingerprint", "offset")}
    assert len(found) == 20 and all(f % 2 for f in found)


def test_empty_lanes_of_the_worked_example():
    x = np.array([0x8F00E600], np.uint64)
    assert int(lanes.empty_lanes(x, 8, 4)[0]) == 0x00800080
    assert int(lanes.has_empty(x, 8, 4)[0]) == 0x00800080
    assert lanes.first_lane(lanes.has_empty(x, 8, 4), 8)[0] == 0


def test_match_of_the_worked_example():
    got = lanes.match_lanes(np.array([0x8F00DC00], np.uint64), np.array([0x9CBCDCFC], np.uint64), 8, 4)
    assert int(got[0]) == 0x00008000


def test_a_borrow_does_not_mark_the_lane_above():
    assert int(lanes.empty_lanes(np.array([0x0100], np.uint64), 8, 2)[0]) == 0x0080


@pytest.mark.parametrize("q", [1, 3, 5, 8, 13, 16, 31, 32, 33, 61, 64])
def test_pack_and_fetch_give_back_values(q):
    values = np.random.default_rng(q).integers(0, 1 << min(q, 62), 1000).astype(np.uint64)
    words = lanes.pack(values, q)
    assert (lanes.unpack(words, 1000, q) == values).all()
    if 2 * q <= 64:
        at = np.arange(999)
        assert (lanes.fetch(words, at, q, 2) == (values[:-1] | values[1:] << np.uint64(q))).all()


@pytest.mark.parametrize("name", ALL_VARIANTS)
@pytest.mark.parametrize("k", [3, 8, 14, 29])
def test_answers_are_those_of_the_stored_signatures(name, k):
    # tables with one slot an address are far from their limit only at a fraction of the threshold
    spec = sized(variant(name, k), len(KEYS), load=0.25 if name[2] == "1" else None)
    words, stats = cuckoo.build(KEYS, spec)
    assert stats["status"] == "ok"
    assert cuckoo.contains(words, KEYS, spec).all()
    stored = set(zip(*(x.tolist() for x in cuckoo.entries(KEYS, spec))))
    expected = [pair in stored for pair in zip(*(x.tolist() for x in cuckoo.entries(OTHERS, spec)))]
    assert cuckoo.contains(words, OTHERS, spec).tolist() == expected
    assert stats["n_stored"] == len(stored)


@pytest.mark.parametrize("name", ALL_VARIANTS)
def test_partner_leads_back_and_differs(name):
    spec = sized(variant(name, 8), 5000)
    address, fp = cuckoo.first_address(KEYS, spec), cuckoo.fingerprints(KEYS, spec)
    other = cuckoo.partner(address, fp, spec)
    assert ((0 <= other) & (other < spec.n_addr)).all()
    assert (cuckoo.partner(other, fp, spec, back=True) == address).all()
    if spec.rule in ("signed", "xor"):
        assert (other != address).all()


@pytest.mark.parametrize("name", VARIANTS)
def test_order_and_kernel_do_not_change_answers(name):
    spec = sized(variant(name, 6), len(KEYS))
    words, _ = cuckoo.build(KEYS, spec)
    again, _ = cuckoo.build(KEYS[::-1], replace(spec, max_walk=9000))
    assert (cuckoo.contains(words, OTHERS, spec) == cuckoo.contains(again, OTHERS, spec)).all()
    address, fp = cuckoo.distinct_entries(*cuckoo.entries(KEYS, spec))
    base = cuckoo._bases(address, fp, spec)
    slots = np.full(spec.n_slots, -1, np.int64)
    ok, n, lengths = cuckoo.walk(base, spec.l, slots, np.arange(len(fp)), 10_000, np.random.default_rng(1))
    assert ok and n == len(fp) == len(lengths)
    one = lanes.pack(cuckoo.encode(slots, address, fp, spec), spec.slot_bits)
    assert (cuckoo.contains(one, OTHERS, spec) == cuckoo.contains(words, OTHERS, spec)).all()


def test_two_slot_buckets_cannot_be_filled_to_92_percent():
    spec = sized(variant("b22", 10, max_walk=2000), 20_000, load=0.92)
    _, stats = cuckoo.build(mix_np(np.arange(20_000)), spec)
    assert stats["status"] == "failed"


@pytest.mark.parametrize("n", [0, 1, 2, 5])
@pytest.mark.parametrize("name", ["w21", "w22", "b24"])
def test_tiny_tables(n, name):
    for k in (1, 3, 60):
        spec = sized(variant(name, k), n)
        words, stats = cuckoo.build(KEYS[:n], spec)
        assert stats["status"] == "ok"
        assert cuckoo.contains(words, KEYS[:n], spec).all()
        if n == 0:
            assert not cuckoo.contains(words, OTHERS, spec).any()


def test_plain_insertion_of_too_many_copies_fails_and_lookup_first_does_not():
    same = np.full(20, KEYS[0])
    spec = sized(variant("w22", 8), 40)
    assert cuckoo.build(same, replace(spec, mode="insert", max_walk=200))[1]["status"] == "failed"
    assert cuckoo.build(same, spec)[1]["n_stored"] == 1


def test_later_insertion_and_deletion():
    spec = sized(variant("w22", 10, mode="insert"), len(KEYS))
    words, _ = cuckoo.build(KEYS[:2000], spec)
    words, stats = cuckoo.build(KEYS[2000:], spec, lanes.unpack(words, spec.n_slots, spec.slot_bits))
    assert stats["status"] == "ok" and cuckoo.contains(words, KEYS, spec).all()
    words, done = cuckoo.delete(words, KEYS[:2000], spec)
    assert done.all() and cuckoo.contains(words, KEYS[2000:], spec).all()
    assert cuckoo.contains(words, KEYS[:2000], spec).mean() < 0.01
    with pytest.raises(ValueError):
        cuckoo.delete(words, KEYS[:1], replace(spec, mode="lookup_insert"))


@pytest.mark.parametrize("kind", ["bloom", "blocked_bloom", "choice_bloom", "quotient", "vector_quotient", "prefix_vector", "prefix_cuckoo", "static_xor", "exact"])
def test_baselines_miss_no_member_and_keep_their_rate(kind):
    spec = baselines.sized_any(baselines.baseline(kind, 8), len(KEYS))
    words, stats = baselines.build_kernel(KEYS, spec)
    assert stats["status"] == "ok"
    assert baselines.contains_kernel(words, KEYS, spec).all()
    rate = baselines.contains_kernel(words, OTHERS, spec).mean()
    assert rate < 1.35 * 2.0**-8 if kind != "exact" else rate == 0
    assert baselines.spec_from_json(spec.to_json()) == spec


def test_quotient_positions_are_those_of_placing_one_after_the_other():
    q = np.sort(np.random.default_rng(2).integers(0, 300, 250))
    taken, expected = -1, []
    for x in q.tolist():
        taken = max(x, taken + 1)
        expected.append(taken)
    assert baselines.quotient_positions(q).tolist() == expected


def test_exact_tables_reach_loads_near_their_thresholds():
    for layout, l in (("bucket", 2), ("window", 2), ("bucket", 4)):  # noqa: E741
        n_addr = 5000
        slots = n_addr + l - 1 if layout == "window" else n_addr * l
        n = int(slots * 0.97 * threshold(layout, l))
        assert cuckoo.exact_table(np.arange(n), n_addr, l, layout).ok


def test_published_figures():
    assert models.overhead("classic", 8, worst=True) == pytest.approx(2.887, abs=1e-3)
    assert models.overhead("windowed", 8, worst=True) == pytest.approx(1.321, abs=1e-3)
    assert models.overhead("quotient", 8, worst=True) == pytest.approx(2.665, abs=1e-3)
    assert models.overhead("vector_quotient", 8, worst=True) == pytest.approx(2.933, abs=1e-3)
    assert models.overhead("prefix", 8) == pytest.approx(1.359, abs=1e-3)
    assert 1.05 * 1.3 == pytest.approx(1.365) and 1.06 * 1.2 == pytest.approx(1.272)
    assert models.break_even() == 102
    assert models.balance(10**8, 10) == (10**7, pytest.approx(3000))
    assert models.table_overhead("window", 2, 8) == pytest.approx(1.3218, abs=1e-4)
    assert models.table_overhead("bucket", 4, 14) == pytest.approx(1.2639, abs=1e-4)
    assert {models.fpr_bound(p, 2, 8) for p in (0.0, 0.25, 1.0)} == {2.0**-8}


@pytest.mark.parametrize("name", VARIANTS)
@pytest.mark.parametrize("k", [3, 5, 8])
def test_load_and_rate_follow_the_models(name, k):
    n = 30_000
    keys, others = mix_np(np.arange(n)), mix_np(np.arange(n, 6 * n))
    spec = sized(variant(name, k), n)
    words, stats = cuckoo.build(keys, spec)
    load = stats["n_stored"] / spec.n_slots
    assert load == pytest.approx(models.predicted_load(spec, n), rel=0.01)
    expected = models.predicted_fpr(spec, load)
    rate = cuckoo.contains(words, others, spec).mean()
    assert abs(rate - expected) < 5 * np.sqrt(expected / len(others)) + 0.03 * expected


def test_lines_touched_match_the_share_of_windows_across_two_lines():
    spec = sized(variant("w24", 13), 4000)  # 16-bit slots
    lines = cuckoo.lines_touched(KEYS, spec)
    assert lines.mean() == pytest.approx(2 + 2 * models.two_line_share(4, 16), abs=0.03)


@pytest.mark.parametrize("name", [*VARIANTS, "b24xor", "b22mirror"])
def test_large_tables_are_filled_piece_by_piece_in_little_memory(name, monkeypatch):
    import tracemalloc

    h = mix_np(np.arange(300_000) % 290_000)
    spec = sized(variant(name, 10), 290_000)
    _, whole = cuckoo.build(h[:100], spec)
    monkeypatch.setattr(cuckoo, "PIECE", 1 << 14, raising=False)
    tracemalloc.start()
    words, stats = cuckoo.build(h, spec)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 60 * len(h) and stats["status"] == "ok" and whole["status"] == "ok"
    want = {tuple(x) for x in np.stack(cuckoo.entries(h, spec), 1).tolist()}
    got = cuckoo.decode(lanes.unpack(words, spec.n_slots, spec.slot_bits), spec)
    address = got["address"] if spec.rule == "signed" else np.minimum(got["address"], cuckoo.partner(got["address"], got["fp"], spec))
    assert len(address) == len(want) and set(zip(address.tolist(), got["fp"].tolist())) == want


@pytest.mark.parametrize("kind", ["bloom", "blocked_bloom", "choice_bloom", "quotient", "vector_quotient", "prefix_vector", "prefix_cuckoo", "static_xor"])
def test_baselines_of_many_keys_are_built_piece_by_piece_in_little_memory(kind, monkeypatch):
    import tracemalloc

    h = mix_np(np.arange(300_000))
    h = np.concatenate([h, h[:1000]])
    spec = baselines.sized_any(baselines.baseline(kind, 8), len(h))
    whole, stats = baselines.build_kernel(h, spec)
    monkeypatch.setattr(cuckoo, "PIECE", 4096)
    monkeypatch.setattr(baselines, "MOST_FLAGS", 1 << 20)
    tracemalloc.start()
    words, again = baselines.build_kernel(h, spec)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert again == stats and baselines.contains_kernel(words, h, spec).all()
    assert kind in ("static_xor", "prefix_cuckoo") or (words == whole).all()  # which slots these give a key depends on the pieces
    assert peak < 30 * len(h), peak / len(h)


def test_mixing_is_undone():
    from fpfilter.functions.hashing import unmix_np

    assert (unmix_np(mix_np(KEYS)) == KEYS).all()


@pytest.mark.parametrize("one_by_one", [0, 1 << 20])
def test_one_filling_tells_the_first_failures_of_all_limits(monkeypatch, one_by_one):
    monkeypatch.setattr(cuckoo, "ONE_BY_ONE", one_by_one)
    h = mix_np(np.arange(20_000))
    for name in ("w22", "b24"):
        spec = replace(variant(name, 12), n_addr=20_000 // (1 if name[0] == "w" else 4))
        together = cuckoo.fill_until_failure(h, spec, 3, (1, 10, 100, 1000))
        assert together == [cuckoo.fill_until_failure(h, spec, 3, (cap,))[0] for cap in (1, 10, 100, 1000)]
        assert together == sorted(together) and together[0] < 0.4  # no key is left out where a limit is met early


def test_walks_with_counts_of_free_slots_are_those_without():
    h = mix_np(np.arange(9000))
    for name in ("w22", "w24", "b22", "b24"):
        spec = replace(variant(name, 12), n_addr=9000 // (1 if name[0] == "w" else int(name[2])))
        base = cuckoo._bases(*cuckoo.entries(h, spec), spec)
        got = cuckoo._walks(base, spec.l, np.full(spec.n_slots, -1, np.int64), 0, (50,), 4)
        _, n, _ = cuckoo.walk(base, spec.l, np.full(spec.n_slots, -1, np.int64), np.arange(len(base)), 50, np.random.default_rng(4))
        assert got == {50: n} and n < len(base)


@pytest.mark.parametrize("one_by_one", [0, 1 << 20])
@pytest.mark.parametrize("name", ["w22", "w24", "b22", "b24"])
def test_long_walks_beside_the_process_end_where_those_within_do(monkeypatch, name, one_by_one):
    from fpfilter.operators import native

    monkeypatch.setattr(cuckoo, "ONE_BY_ONE", one_by_one)
    monkeypatch.setattr(cuckoo, "PIECE", 1 << 13)  # draws are left over from piece to piece
    h, caps = mix_np(np.arange(20_000)), (1, 10, 1000, 10_000)
    spec = replace(variant(name, 12), n_addr=20_000 // (1 if name[0] == "w" else int(name[2])))
    within = cuckoo.fill_until_failure(h, spec, 3, caps)  # few items
    monkeypatch.setattr(native, "WORTH", 1)
    assert native.helper() is not None
    assert cuckoo.fill_until_failure(h, spec, 3, caps) == within
    native.helper().process.kill()  # a helper that fails is done without
    assert cuckoo.fill_until_failure(h, spec, 3, caps) == within and native.helper() is None
    native.ended()


def test_without_java_long_walks_stay_within_the_process(monkeypatch):
    from fpfilter.operators import native

    native.ended()
    monkeypatch.setattr(native.shutil, "which", lambda *_: None)
    monkeypatch.setattr(native, "WORTH", 1)
    h = mix_np(np.arange(5000))
    assert 0.9 < cuckoo.fill_until_failure(h, replace(variant("w22", 12), n_addr=4999), 3, [1000])[0] < 0.98
    assert native.helper() is None
    native.ended()


@pytest.mark.parametrize("k", [4, 10])
@pytest.mark.parametrize("name", ["w22", "w24", "b22", "b24", "w23"])
def test_tables_beside_the_process_hold_the_same_entries(monkeypatch, name, k):
    from fpfilter.operators import native

    monkeypatch.setattr(cuckoo, "PIECE", 1 << 13)
    h, other = mix_np(np.arange(40_000)), mix_np(np.arange(40_000) + (1 << 60))
    for mode in ("lookup_insert", "insert"):
        spec = sized(variant(name, k, mode=mode), len(h))
        table, (words, stats) = cuckoo.table_beside(h, spec), cuckoo.build(h, spec)
        assert {**table.stats, "max_walk": 0, "sum_walk": 0} == {**stats, "max_walk": 0, "sum_walk": 0}
        if stats["status"] == "ok":
            held = [sorted(zip(*(cuckoo.decode(lanes.unpack(x, spec.n_slots, spec.slot_bits), spec)[c].tolist() for c in ("address", "fp")))) for x in (table.words(), words)]
            assert held[0] == held[1]
            assert table.contains(h).all() and (table.contains(other) == cuckoo.contains(words, other, spec)).all()
    small = replace(spec, n_addr=spec.n_addr * 3 // 4)
    assert cuckoo.table_beside(h, small).stats["status"] == "failed"
    native.helper().process.kill()  # a helper that fails is done without
    assert cuckoo.table_beside(h, spec) is None and native.helper() is None
    native.ended()
