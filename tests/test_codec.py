import random

import pytest

from vboost.functions import codec, costs
from vboost.functions.codec import Budget
from vboost.he.base import Mock
from vboost.he.paillier import keygen


def test_worked_example():
    b = Budget(10**6)
    assert (b.b_g, b.b_h, b.b_gh, b.slots) == (74, 73, 147, 6)
    g = b.amplified(8)
    assert (g.b_g, g.b_h, g.b_gh, g.slots) == (77, 76, 153, 6)


def test_cost_reductions():
    r = costs.reduction(10**6, 2000)
    assert round(r["computation"], 4) == 0.7499 and round(r["endecryption"], 2) == 0.78 and round(r["communication"], 2) == 0.78


@pytest.mark.parametrize("g,h", [(1.0, 1.0), (-1.0, 1.0), (0.0, 0.0)])
def test_extremes_do_not_carry(g, h):
    n, b = 1000, Budget(1000, 20)
    total = sum(codec.pack(g, h, b) for _ in range(n))
    assert codec.unpack(total, n, b) == (int(n * g * 2**20), int(n * h * 2**20))


def test_one_bit_less_overflows():
    b = Budget(1000, 20)
    narrow = sum((int((1.0 + b.g_off) * 2**20) << (b.b_h - 1)) + 2**20 for _ in range(1000))
    assert narrow & ((1 << (b.b_h - 1)) - 1) != 1000 * 2**20


def test_compression_round_trip():
    b = Budget(10**6)
    for k in range(1, b.slots + 1):
        values = [random.Random(k).getrandbits(b.b_gh) for _ in range(k)]
        assert codec.decompress(codec.compress(values, b), k, b) == values
    with pytest.raises(ValueError):
        codec.compress([1] * (b.slots + 1), b)


@pytest.mark.parametrize("k", range(1, 26))
def test_multi_class_round_trip(k):
    b, rng = Budget(50, 20, iota=255), random.Random(k)
    rows = [([rng.uniform(-1, 1) for _ in range(k)], [rng.random() for _ in range(k)]) for _ in range(50)]
    packed = [codec.pack_mo(g, h, b) for g, h in rows]
    assert len(packed[0]) == b.n_k(k)
    sums = codec.unpack_mo([sum(c) for c in zip(*packed)], 50, k, b)
    for j in range(k):
        assert sums[j][0] == sum(int((g[j] + 1) * 2**20) for g, _ in rows) - 50 * 2**20
        assert sums[j][1] == sum(int(h[j] * 2**20) for _, h in rows)


def test_paillier_laws():
    key = keygen(256, seed=3)
    a, b = key.encrypt(41), key.encrypt(1)
    assert key.decrypt(key.public().add(a, b)) == 42
    assert key.decrypt(key.public().scale(a, 3)) == 123
    assert key.decrypt(key.public().sub(a, b)) == 40
    assert key.encrypt(41) != a and key.decrypt(a) == key.decrypt_plain(a) == 41
    key.pool(2)
    assert key.decrypt(key.encrypt(7)) == 7
    with pytest.raises(OverflowError):
        key.encrypt(key.n)


def test_mock_counts():
    m = Mock(255)
    m.decrypt(m.fold([m.encrypt(i) for i in range(5)]))
    assert m.counts == {"enc": 5, "adds": 4, "dec": 1}
