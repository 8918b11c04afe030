"""Ciphers by arrays: the same bytes, cells and counts as one by one."""

import threading

import numpy as np
import pyarrow as pa
import pytest

from vboost import experiments
from vboost.functions import codec
from vboost.functions.codec import Budget
from vboost.he.base import Backend, Mock
from vboost.he.paillier import keygen
from vboost.plans import protocol


class Few(Mock):
    """No call for each row: only cells may be added one by one."""

    calls = 0

    def encrypt(self, m):
        raise AssertionError("one by one")

    def add(self, a, b):
        self.calls += 1
        return super().add(a, b)


def gradients(n, classes):
    rng = np.random.default_rng(1)
    g, h = rng.uniform(-1, 1, (n, classes)), rng.uniform(0, 1, (n, classes))
    g[0], g[1], h[0], h[1] = -1, 1, 0, 1
    return g, h


@pytest.mark.parametrize("budget, classes, packing", [(Budget(400), 1, True), (Budget(3_600_000), 1, False), (Budget(900).amplified(8.0), 5, True), (Budget(900, rounding="round", iota=255), 3, True), (Budget(900, g_max=1e3, g_off=1e3), 1, True)])
def test_ciphers_of_arrays_are_those_of_single_rows(budget, classes, packing):
    g, h = gradients(200, classes)
    key = Mock(budget.iota)
    plain = [codec.pack_mo(x, y, budget) if classes > 1 else [codec.pack(x[0], y[0], budget)] if packing else codec.apart(x[0], y[0], budget) for x, y in zip(g.tolist(), h.tolist())]
    found = protocol._encrypted(g, h, key, budget, packing)
    assert [[c.tobytes() for c in row] for row in found] == [[key.encrypt(m) for m in row] for row in plain]
    assert protocol.matrix_of(protocol.lists_of(found).slice(7, 90)).tolist() == found[7:97].tolist()
    some = keygen(256, 3)
    if budget.iota <= some.iota or classes == 1:
        opened = protocol._encrypted(g[:5], h[:5], some, budget, packing)
        assert [[some.decrypt(c.tobytes()) for c in row] for row in opened] == plain[:5]


def test_bounds_hold_for_arrays():
    for g, h in ((1.5, 0.5), (0.5, -0.1), (float("nan"), 0.5)):
        with pytest.raises(OverflowError):
            protocol._encrypted(np.array([[0.0], [g]]), np.array([[0.0], [h]]), Mock(), Budget(9), True)


@pytest.mark.parametrize("default", [None, [2, 0]])
def test_cells_are_folded_without_a_call_for_each_row(default):
    n, rng, key = 3000, np.random.default_rng(2), Few()
    bins, node = rng.integers(0, 4, (n, 2)), rng.integers(3, 6, n)
    c = protocol._encrypted(*gradients(n, 1), key, Budget(n), False)
    lists = pa.array(bins.tolist(), pa.list_(pa.int32()))
    rows = pa.RecordBatch.from_arrays([pa.array(node, pa.int32()), lists, protocol.lists_of(c)], names=["node", "bins", "c"])
    made = [r for b in protocol._fold_rows(key, 65_536, default)(iter([rows.slice(0, 2000), rows.slice(2000)])) for r in b.to_pylist()]
    assert key.calls <= 2 * len(made)  # once a cell, cipher and further batch
    want = {}
    for x, k, row in zip(bins.tolist(), node.tolist(), c):
        for fid, b in enumerate(x):
            if default is None or b != default[fid]:
                want.setdefault((k, fid, b), []).append(row)
        if default is not None:
            want.setdefault((k, protocol.WHOLE, 0), []).append(row)
    one = lambda v, i: Backend.fold(Mock(), [x[i].tobytes() for x in v])
    assert {(r["node"], r["fid"], r["bin"]): (r["cnt"], r["adds"], r["c"]) for r in made} == {k: (len(v), 2 * len(v) - 2, [one(v, 0), one(v, 1)]) for k, v in want.items()}


def test_folds_of_places_agree():
    rng = np.random.default_rng(3)
    full = rng.integers(0, 256, (300, 129), dtype=np.uint8)
    full[:, 0] = 0
    at = rng.integers(0, 9, 300) * 5
    for c in (full, np.zeros_like(full), full[:1]):
        assert Mock().fold_by(at[: len(c)], c) == Backend.fold_by(Mock(), at[: len(c)], c)
    key = keygen(128, 1)
    c = key.encrypt_fields(np.arange(20).reshape(10, 2), [40, 0])
    folded = key.fold_by(np.arange(10) % 2, c)
    assert {k: key.decrypt(v) for k, v in folded.items()} == {j: sum((2 * i << 40) + 2 * i + 1 for i in range(j, 10, 2)) for j in (0, 1)}


#: Of the runs one after the other, with a call for each row.
BASE, LEAN = [30.740844, 31.346532], [4.538871, 4.698126]


def test_scale_runs_side_by_side_count_the_same(spark, monkeypatch):
    sf = "/root/testdata/sf0.001"
    seen = {}
    inner = experiments._counted
    monkeypatch.setattr(experiments, "_counted", lambda *a: seen.setdefault(threading.get_ident(), []).append(a[-1]) or inner(*a))
    rows = experiments.x10_scale(spark, sf, (1,)).collect()
    assert len(seen) > 1  # side by side
    assert [(r["n"], r["passive_features"]) for r in rows] == [(1500, 1), (1500, 2)]
    assert [round(r["base_seconds"], 6) for r in rows] == BASE and [round(r["lean_seconds"], 6) for r in rows] == LEAN
