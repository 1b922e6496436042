from __future__ import annotations

import math

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from densekeys import measures
from densekeys.functions import kernel
from densekeys.functions.hashing import PRIME, ChunkTables, LinearHash, MixedValues, MixingHash, Sums, ragged
from densekeys.functions.rank import below, directory, packed, popcount, rank, theory_steps
from densekeys.operators.baselines import METHODS
from densekeys.functions.hashing import splitmix


def test_modulus_has_room_for_the_largest_product():
    s = Sums(np.array([0], np.uint64), np.array([PRIME - np.uint64(1)], np.uint64))
    assert s.values(np.array([PRIME - np.uint64(1)]), np.array([1 << 62], np.uint64))[0] == 1


@given(st.lists(st.binary(max_size=20), min_size=1, max_size=20))
@settings(max_examples=40, deadline=None)
def test_linear_hash_is_linear_and_ignores_zero_padding(keys):
    h = LinearHash(3, 24)
    padded = [k.ljust(24, b"\0") for k in keys]
    assert (h(*ragged(keys)) == h(*ragged(padded))).all()
    x, y = padded[0], padded[-1]
    both = bytes(a ^ b for a, b in zip(x, y, strict=True))
    a, b, c = (h(*ragged([k]))[0] for k in (x, y, both))
    assert ((a ^ b) == c).all()


def test_hashes_do_not_depend_on_the_order_of_keys():
    keys = [b"k" * (i % 30) + bytes([i]) for i in range(200)]
    back = list(reversed(keys))
    for h in (LinearHash(1, 40), MixingHash(1)):
        assert (h(*ragged(keys)) == h(*ragged(back))[::-1]).all()
        assert len(np.unique(h(*ragged(keys)), axis=0)) == 200


def test_chunks_never_meet_across_the_two_functions():
    y = ChunkTables(1).split(np.random.default_rng(0).integers(0, 2**32, (100, 4)).astype(np.uint32))
    assert not np.isin(y | 1, y).any() and (y < 1 << 15).all()


@pytest.mark.parametrize("left,right,rest", [([0], [0], 0), ([0, 0], [0, 0], 2), ([0, 0, 1, 1], [0, 1, 0, 1], 4), ([0, 1, 1, 2], [0, 0, 1, 1], 0)])
def test_peeling_finds_cycles(left, right, rest):
    left, right = np.array(left), np.array(right) + 5
    remaining, rounds = kernel.peel(left, right, 10)
    assert len(remaining) == rest
    if not rest:
        labels = kernel.labels_of(left, right, rounds, 10)
        slots = np.where(labels[left] ^ labels[right], right, left)
        assert len(set(slots.tolist())) == len(left)


@given(st.lists(st.integers(1, 60), min_size=1, max_size=12), st.sampled_from([0.045, 0.3]), st.booleans(), st.sampled_from([32, 128, 256]))
@settings(max_examples=40, deadline=None)
def test_functions_are_bijective(sizes, eps, compressed, kappa):
    sizes = np.array(sizes)
    numbers = np.arange(len(sizes)) * 3
    words = (splitmix(np.arange(4 * sizes.sum(), dtype=np.uint64)) >> np.uint64(32)).astype(np.uint32).reshape(-1, 4)
    sums = MixedValues().sums(words)
    built = kernel.build(numbers, sizes, sums, eps, 9)
    labels, occupied = kernel.packed_bits(built, eps, compressed)
    tau = kernel.side_sizes(sizes, eps)
    f = kernel.Functions(numbers, sizes, built.seeds, np.cumsum(sizes) - sizes, labels, occupied, eps, kappa, compressed, 2 * (np.cumsum(tau) - tau))
    slots, ids = f.evaluate(np.repeat(numbers, sizes), sums)
    assert sorted(ids.tolist()) == list(range(sizes.sum())) and len(set(slots.tolist())) == sizes.sum() and slots.max() < 2 * tau.sum()
    for bits in (8, 16):
        assert (f.evaluate(np.repeat(numbers, sizes), sums, bits)[1] == ids).all()
    assert f.evaluate(np.array([1]), MixedValues().sums(words[:1]))[1][0] == -1  # an empty bucket
    assert not built.labels[~built.occupied].any()


@given(st.lists(st.booleans(), min_size=1, max_size=700), st.sampled_from([8, 64, 128, 256]))
@settings(max_examples=40, deadline=None)
def test_rank_counts_what_is_below(flags, kappa):
    flags = np.array(flags)
    sizes = np.array([len(flags)])
    entries, base = directory(flags, sizes, kappa)
    at = np.arange(len(flags))
    got = rank(packed(flags, sizes), np.zeros(len(at), int), entries, np.zeros(len(at), int), at, kappa)
    assert (got == np.cumsum(flags) - flags).all()


def test_popcount_and_below():
    x = np.array([0, 1, 2**64 - 1], np.uint64)
    for bits in ("native", 16, 8):
        assert popcount(x, bits).tolist() == [0, 1, 64]
    assert below(x, np.array([3, 0, 64])).tolist() == [0, 0, 2**64 - 1]


@pytest.mark.parametrize("method", METHODS)
@pytest.mark.parametrize("n", [1, 2, 5, 300, 2000])
def test_baselines_number_a_set(method, n):
    prints = splitmix(np.arange(n, dtype=np.uint64))
    assert measures.is_permutation(METHODS[method].build(prints).evaluate(prints), n)


def test_acyclic_baseline_keeps_any_order():
    prints, target = splitmix(np.arange(500, dtype=np.uint64)), np.random.default_rng(1).permutation(500)
    assert (METHODS["sumgraph_acyclic"].build(prints, target=target).evaluate(prints) == target).all()


def test_closed_forms_meet_the_published_numbers():
    assert measures.fixed_bytes() == 1_847_424
    assert round(measures.acyclic_probability(0.045), 2) == 0.33
    assert round(measures.ci95(1.22, 10), 2) == 0.87
    assert abs(measures.phf_bits_model(10**9, 23) - 2.65) < 0.05
    assert measures.collision_bound(10**9, 23) < 1e-15
    assert math.isclose(measures.space_bounds(100)["least_bits"], 144.27, abs_tol=0.01)


def test_more_room_means_fewer_tries():
    words = (splitmix(np.arange(4 * 12800, dtype=np.uint64)) >> np.uint64(32)).astype(np.uint32).reshape(-1, 4)
    sizes = np.full(100, 128)
    tries = [kernel.build(np.arange(100), sizes, MixedValues().sums(words), eps, 1).tries.mean() for eps in (0.01, 0.25, 1.0)]
    assert tries[0] > tries[1] > tries[2] and 1.7 < tries[0] < 3.5


@given(st.lists(st.binary(max_size=9), min_size=1, max_size=30))
@settings(max_examples=40, deadline=None)
def test_chunk_width_changes_tables_only(keys):
    by_byte = LinearHash(5, 9)(*ragged(keys))
    for sigma in (4, 16):
        assert (LinearHash(5, 9, sigma=sigma)(*ragged(keys)) == by_byte).all()


@given(st.lists(st.integers(1, 300), min_size=1, max_size=9), st.sampled_from([0.05, 0.5, 3.0]))
@settings(max_examples=30, deadline=None)
def test_steps_of_the_directory_may_differ_by_bucket(sizes, eps_rank):
    sizes = np.array(sizes)
    rng = np.random.default_rng(int(sizes.sum()))
    flags = rng.random(sizes.sum()) < 0.5
    kappa = theory_steps(sizes, eps_rank)
    entries, base = directory(flags, sizes, kappa)
    assert len(entries) == (-(-sizes // kappa)).sum()
    words = np.concatenate([[0], np.cumsum(-(-sizes // 64))])
    bucket = np.repeat(np.arange(len(sizes)), sizes)
    place = np.arange(len(bucket)) - (np.cumsum(sizes) - sizes)[bucket]
    got = rank(packed(flags, sizes), words[bucket], entries, base[bucket], place, kappa[bucket])
    want = np.concatenate([np.cumsum(f) - f for f in np.split(flags.astype(int), np.cumsum(sizes)[:-1])])
    assert (got == want).all()


@given(st.lists(st.binary(max_size=12), max_size=20), st.integers(0, 5))
@settings(max_examples=40, deadline=None)
def test_columns_are_hashed_as_they_lie(keys, skipped):
    import pyarrow as pa

    from densekeys.plans.fingerprints import key_bytes

    column = pa.array([b"skipped"] * skipped + keys, pa.binary()).slice(skipped)
    data, ends = key_bytes(column)
    assert [data[a:b].tobytes() for a, b in zip(ends, ends[1:], strict=False)] == keys
    for h in (LinearHash(2, 12), LinearHash(2, 12, sigma=16), MixingHash(2)):
        if keys:
            assert (h(data, ends) == h(*ragged(keys))).all()
