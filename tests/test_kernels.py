"""Bit kernels, transformers, offset structures and solvers, against plain Python."""

import itertools
import zlib

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from packgraph.adjacency import transform
from packgraph.adjacency.arrange import KINDS, _cost, _near, local_search, odb_solve, pod_solve
from packgraph.adjacency.transform import FixedWidth, FullVarint, GapVarint, PrefixGroups, RefInterval, zeta_bits
from packgraph.bits import pack as P
from packgraph.core.machine import MachineModel, ceil_lg
from packgraph.fine.relabel import ilp_solve_small
from packgraph.measure.bounds import bound_graph, expected_size_er
from packgraph.offsets.kinds import KINDS as OFFSETS
from packgraph.offsets.kinds import BTree, GapTree, Plain

EXAMPLE = [(0, 4), (0, 6), (4, 6), (2, 4), (2, 6), (1, 3), (1, 5), (3, 5), (5, 7), (3, 7), (6, 7)]
lists = st.lists(st.sets(st.integers(1, 5000), min_size=0, max_size=40).map(sorted), min_size=1, max_size=12)


@given(st.lists(st.tuples(st.integers(0, 63), st.integers(0, 9)), min_size=1, max_size=8), st.randoms())
@settings(max_examples=60, deadline=None)
def test_pack_round_trip(shape, rnd):
    width = np.array([w for w, _ in shape])
    begin = np.concatenate([[0], np.cumsum([n for _, n in shape])])
    values = np.array([rnd.randrange(1 << w) for w, n in shape for _ in range(n)], np.int64)
    payloads = P.pack(values, width, begin)
    assert P.unpack(payloads, width, begin).tolist() == values.tolist()
    for k, (w, n) in enumerate(shape):
        assert [P.field(payloads[k], w, i) for i in range(n)] == values[begin[k] : begin[k + 1]].tolist()
        assert len(payloads[k]) == (w * n + 7) // 8


@given(st.lists(st.lists(st.integers(0, 2**62), max_size=6), min_size=1, max_size=6))
@settings(max_examples=60, deadline=None)
def test_varint_round_trip(rows):
    begin = np.concatenate([[0], np.cumsum([len(r) for r in rows])])
    flat = np.array([x for r in rows for x in r], np.int64)
    payloads = P.varint(flat, begin)
    x, b = P.unvarint(payloads)
    assert x.tolist() == flat.tolist() and b.tolist() == begin.tolist()
    assert [len(p) for p in payloads] == [sum(max(1, -(-v.bit_length() // 7)) for v in r) for r in rows]


def test_references_are_chosen_by_size(monkeypatch):
    """Each list is written once, whatever was tried for it, and in as few bytes as the best reference or none gives."""
    rng = np.random.default_rng(3)
    lists = [np.unique(rng.integers(1, 400, 30)) for _ in range(40)]
    lists = [np.unique(np.concatenate([x, y[: len(y) // 2], np.arange(50, 50 + k % 9)])) for k, (x, y) in enumerate(zip(lists, lists[1:]))]
    begin = np.concatenate([[0], np.cumsum([len(x) for x in lists])])
    called = []
    monkeypatch.setattr(transform, "varint", lambda *a, f=transform.varint: called.append(a) or f(*a))
    t = RefInterval()
    sizes = [len(x) for x in t.encode(np.concatenate(lists), begin, np.arange(len(lists)), 400)[0]]
    assert len(called) == len(lists)
    chain = [0] * len(lists)
    for k, a in enumerate(lists):
        tried = [(len(P.varint(np.array(x := [0, *t._rest(a, k)]), np.array([0, len(x)]))[0]), 0)]
        for r in range(1, min(7, k) + 1):
            b = lists[k - r]
            hit = np.isin(b, a)
            if hit.any() and chain[k - r] < 3:
                blocks = [len(list(g)) for _, g in itertools.groupby([True, *hit.tolist()])]
                blocks[0] -= 1
                x = [r, len(blocks), *blocks, *t._rest(a[~np.isin(a, b)], k)]
                tried.append((len(P.varint(np.array(x), np.array([0, len(x)]))[0]), r))
        size, r = min(tried)
        chain[k] = chain[k - r] + 1 if r else 0
        assert sizes[k] == size


@pytest.mark.parametrize("t", [FixedWidth(False), FixedWidth(True), FixedWidth(False, True), FixedWidth(True, True), FullVarint(), GapVarint(), PrefixGroups(4, 13), PrefixGroups(4, 13, True), PrefixGroups(13, 13), RefInterval()], ids=lambda t: t.name)
@given(lists)
@settings(max_examples=25, deadline=None)
def test_transformers_decode_what_they_encode(t, rows):
    begin = np.concatenate([[0], np.cumsum([len(r) for r in rows])]).astype(np.int64)
    flat = np.array([x for r in rows for x in r], np.int64)
    origin = np.arange(1, len(rows) + 1) * 7
    payloads, width, first = t.encode(flat, begin, origin, 5000)
    assert t.decode(payloads, np.asarray(width), np.asarray(first), np.diff(begin), origin, 5000).tolist() == flat.tolist()


def test_reference_coding_copies_lists():
    a = np.array([3, 9, 27, 81, 243] * 2)
    payloads, _, _ = RefInterval().encode(a, np.array([0, 5, 10]), np.array([1, 2]), 300)
    assert len(payloads[1]) < len(payloads[0])
    assert zeta_bits(np.array([1, 2, 8, 64])).tolist() == [3, 4, 7, 11]


@pytest.mark.parametrize("kind", sorted(OFFSETS))
@given(st.sets(st.integers(0, 3000), min_size=1, max_size=200))
@settings(max_examples=15, deadline=None)
def test_select_finds_every_one(kind, ones):
    ones = np.array(sorted(ones))
    s = OFFSETS[kind](ones, int(ones[-1]) + 5)
    assert s.select(np.arange(len(ones))).tolist() == ones.tolist()
    again = OFFSETS[kind].load(bytes(s.raw))
    some = np.arange(len(ones))[::-3]
    assert again.select(some).tolist() == ones[some].tolist()
    assert (again.payload_bits, again.index_bits) == (s.payload_bits, s.index_bits)
    # what is stored: codes, directories, a header of 256 bits (two for the nested vector), and fill to whole words and runs
    assert 8 * len(s.raw) <= s.payload_bits + s.index_bits + 2 * 256 + 4096 + 3 * 64


def test_gaps_beyond_32_bits():
    ones = np.array([5, 2**33, 2**40, 2**40 + 1])
    assert OFFSETS["gap"].load(OFFSETS["gap"](ones, 2**41).raw).select(np.arange(4)).tolist() == ones.tolist()


def test_deflated_sizes_are_those_of_zlib():
    ones = np.cumsum(np.random.default_rng(2).integers(1, 9, 5000))
    raw = np.append(ones, ones[-1] + 3).astype("<u8").tobytes()
    assert OFFSETS["zlib_blocked"](ones, int(ones[-1]) + 3).payload_bits == sum(8 * len(zlib.compress(raw[i : i + 4096], 6)) for i in range(0, len(raw), 4096))
    whole = OFFSETS["zlib"](ones, int(ones[-1]) + 3)
    assert zlib.decompress(whole.parts.tobytes()).endswith(raw) and whole.payload_bits < 8 * len(raw)


@given(st.lists(st.integers(0, 400), min_size=1, max_size=120))
@settings(max_examples=15, deadline=None)
def test_trees_take_inserts(places):
    bits, tree = [0], BTree(np.zeros(0, np.int64), 1, 16)
    gap, ones = GapTree(np.zeros(0, np.int64), 0, 8), []
    for p in places:
        p = min(p, len(bits))
        bits.insert(p, 1)
        tree.insert(p)
        ones = sorted([x + (x >= p) for x in ones] + [p])
        gap.insert(p)
    want = [k for k, b in enumerate(bits) if b]
    assert tree.select(np.arange(len(want))).tolist() == want
    assert gap.select(np.arange(len(ones))).tolist() == ones


def test_plain_directory_is_small():
    ones = np.arange(0, 1_000_000, 3)
    p = Plain(ones, 1_000_000)
    assert p.index_bits <= 0.2 * p.payload_bits


def test_worked_example_optima():
    assert odb_solve(8, EXAMPLE, "mgapa")[0] == 32
    assert pod_solve(8, EXAMPLE)[0] == 32
    assert odb_solve(8, EXAMPLE, "mlina")[0] == min(_cost(_near(8, EXAMPLE), list(p), "mlina") for p in [odb_solve(8, EXAMPLE, "mlina")[1]])
    assert ilp_solve_small(8, [(a + 1, b + 1) for a, b in EXAMPLE])[0] == 14
    for kind in KINDS:
        cost, label = odb_solve(8, EXAMPLE, kind)
        assert abs(_cost(_near(8, EXAMPLE), label, kind) - cost) < 1e-9
        assert cost <= _cost(_near(8, EXAMPLE), local_search(8, EXAMPLE, kind), kind) + 1e-9


def test_widths_and_bounds():
    assert [ceil_lg(x) for x in (0, 1, 2, 3, 4, 5, 2**40, 2**40 + 1)] == [0, 0, 1, 2, 2, 3, 40, 41]
    assert MachineModel((1, 4)).physical_bits(2100) == 2100 * 10 + 8
    assert abs(bound_graph(2**42, 2**46) / 8e12 - 338) < 8
    a, o = expected_size_er(1024, 0.1, 256)
    assert a == 0.1 * 1024 * 1023 * 18 and o == 1024 * 17


@pytest.mark.parametrize("kind", KINDS)
def test_local_search_equals_whole_costs(kind):
    rng = np.random.default_rng(6)
    for n in (2, 9, 40):
        edges = sorted({tuple(sorted(rng.choice(n, 2, replace=False).tolist())) for _ in range(2 * n)})
        near = _near(n, edges)
        order = sorted(range(n), key=lambda v: (len(near[v]), v))
        label = [order.index(v) + 1 for v in range(n)]
        for _ in range(4):
            for p in range(1, n):
                a, b = label.index(p), label.index(p + 1)
                old = _cost(near, label, kind)
                label[a], label[b] = p + 1, p
                if _cost(near, label, kind) >= old - 1e-12:
                    label[a], label[b] = p, p + 1
        assert abs(_cost(near, local_search(n, edges, kind), kind) - _cost(near, label, kind)) < 1e-6
