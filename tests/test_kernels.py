import random

import numpy as np
import pytest

from hybridsort.operators.kernels import KERNELS, blocked_scatter, counting_scatter, kway_merge, lsd_sort, msd_sort


def rows(n, width, values, seed=0):
    rng = random.Random(seed)
    return np.array([[rng.randrange(values) for _ in range(width)] for _ in range(n)], np.uint8).reshape(n, width)


@pytest.mark.parametrize("name", list(KERNELS))
@pytest.mark.parametrize("n", [0, 1, 2, 63, 64, 65, 500])
@pytest.mark.parametrize("values", [1, 2, 256])
def test_kernel_sorts(name, n, values):
    keys = rows(n, 4, values)
    got = keys[KERNELS[name](keys)]
    assert got.tolist() == sorted(keys.tolist())


@pytest.mark.parametrize("name", ["msd", "msd_blocked", "lsd", "stable"])
def test_stable_kernels_keep_input_order(name):
    keys = rows(400, 2, 3)
    order = KERNELS[name](keys).tolist()
    assert order == sorted(range(400), key=lambda i: (keys[i].tolist(), i))


def test_reversed_and_presorted():
    keys = np.arange(300, dtype=">u4").view(np.uint8).reshape(-1, 4)
    assert msd_sort(keys, 8).tolist() == list(range(300))
    assert msd_sort(keys[::-1], 8).tolist() == list(range(299, -1, -1))


def test_scatters_agree():
    digit = rows(5000, 1, 256)[:, 0]
    a, b = counting_scatter(digit), blocked_scatter(digit, 128)
    assert a[0].tolist() == b[0].tolist() and a[1].tolist() == b[1].tolist()


def test_two_digit_passes():
    keys = rows(300, 5, 256)
    assert lsd_sort(keys, 2).tolist() == lsd_sort(keys, 1).tolist()


def test_merge():
    runs = [rows(20 * s, 3, 3, s) for s in (3, 0, 1, 5, 2)]
    runs = [r[KERNELS["stable"](r)] for r in runs]
    every = np.concatenate(runs)
    assert kway_merge(runs).tolist() == sorted(range(len(every)), key=lambda i: (every[i].tolist(), i))
    assert kway_merge([]).tolist() == [] and kway_merge(runs[:1]).tolist() == list(range(60))


@pytest.mark.parametrize("limit", [None, 0, 8, 1000])
@pytest.mark.parametrize("name", ["msd", "msd_blocked"])
def test_limits_do_not_change_the_order(name, limit):
    for n, width, values in ((3000, 17, 2), (2500, 1, 7), (1200, 9, 256)):
        keys = rows(n, width, values)
        assert KERNELS[name](keys, limit).tolist() == sorted(range(n), key=lambda i: (keys[i].tolist(), i))
