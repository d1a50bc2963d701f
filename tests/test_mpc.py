import numpy as np
import pytest

from veilmatch.operators import mpc, secure

U = np.uint64
EDGES = np.array([0, 1, -1, 2, 2**31, -(2**31), 2**61, -(2**61), 12345], np.int64)


def grid():
    a, b = np.meshgrid(EDGES, EDGES)
    return a.ravel(), b.ravel()


@pytest.mark.parametrize("what,rule", [("multiply", lambda a, b: a.view(U) * b.view(U)), ("greater", lambda a, b: (a > b).astype(U)), ("equal", lambda a, b: (a == b).astype(U))])
def test_kernels(what, rule):
    a, b = grid()
    rng = np.random.default_rng(2)
    a, b = np.concatenate((a, rng.integers(-(2**60), 2**60, 5000))), np.concatenate((b, rng.integers(-(2**60), 2**60, 5000)))
    s = mpc.Session("k")
    got = mpc.reveal(getattr(s, what)(s.split(a.view(U)), s.split(b.view(U))))
    assert (got == rule(a, b)).all()


def test_split_opens_and_one_share_is_uniform():
    s = mpc.Session("k")
    v = np.zeros(100_000, U)
    a = s.split(v)
    assert (mpc.reveal(a) == v).all()
    for part in a:
        counts = np.bincount(part.view(np.uint8), minlength=256)
        assert ((counts - counts.mean()) ** 2 / counts.mean()).sum() < 400


def test_gram_equals_the_product():
    rng = np.random.default_rng(0)
    x, y = rng.integers(0, 2, (7, 900)).astype(U), rng.integers(0, 2, (9, 900)).astype(U)
    s = mpc.Session("k")
    assert (mpc.reveal(s.gram(s.split(x), s.split(y))) == x @ y.T).all()


@pytest.mark.parametrize("m", [1, 2, 3, 5, 8, 33])
def test_tournament_equals_scan_and_max(m):
    rng = np.random.default_rng(m)
    num, den = rng.integers(0, 50, (6, m)), rng.integers(50, 60, (6, m))
    num[:, m // 2 :] = num[:, :1]
    den[:, m // 2 :] = den[:, :1]
    den[0] = 0
    num[0] = 0
    ids = np.broadcast_to(np.arange(1, m + 1), num.shape)
    want = [max(range(m), key=lambda j: (num[i, j] / den[i, j] if den[i, j] else 0, -j)) + 1 for i in range(6)]
    for order in ("tree", "scan"):
        s = mpc.Session("k", order)
        n, d, i = (s.split(v.astype(U)) for v in (num, den, ids))
        won = secure.tournament(s, n, secure.guarded(s, d), i, order)
        assert mpc.reveal(won[2]).tolist() == want


def test_traffic_is_linear_and_rounds_grow_by_a_constant():
    words, rounds = [], []
    for m in (8, 16, 32):
        s = mpc.Session("k")
        v = [s.split(np.ones((1, m), U)) for _ in range(3)]
        secure.tournament(s, *v)
        words.append(sum(s.bytes_.values()))
        rounds.append(s.rounds["tournament"])
    assert rounds[2] - rounds[1] == rounds[1] - rounds[0] > 0
    assert abs((words[2] - words[1]) - 2 * (words[1] - words[0])) <= 0.01 * words[2]
