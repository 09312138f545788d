import numpy as np
from hypothesis import given, settings
from hypothesis import strategies as st

from corridor.baselines import codecs
from corridor.functions import vwidth


def brute(u):
    best = [0] + [1 << 60] * len(u)
    for i in range(1, len(u) + 1):
        for n in vwidth.LENGTHS:
            if n <= i:
                best[i] = min(best[i], best[i - n] + vwidth.HEADER + n * max(x.bit_length() for x in u[i - n : i]))
    return best[-1]


@settings(max_examples=150, deadline=None)
@given(st.lists(st.one_of(st.integers(0, 3), st.integers(0, 1000), st.integers(0, 1 << 50)), max_size=80))
def test_shared_width_code(u):
    a = np.array(u, np.uint64)
    assert vwidth.size(a) == brute(u)
    raw = vwidth.encode(a)
    assert len(raw) == (vwidth.size(a) + 7) // 8
    assert vwidth.decode(raw, len(u)).tolist() == u


def test_sign_maps_are_injective():
    i = np.arange(-5000, 5001)
    for kind in ("dense", "sparse"):
        u = vwidth.zigzag(i, kind)
        assert len(set(u.tolist())) == len(i) and (vwidth.unzigzag(u, kind) == i).all()


@settings(max_examples=60, deadline=None)
@given(st.binary(max_size=300))
def test_byte_transforms(data):
    last, row = codecs.bwt(data)
    assert codecs.unbwt(last, row) == data
    assert codecs.unfront(codecs.front(data)) == data


@settings(max_examples=40, deadline=None)
@given(st.lists(st.integers(0, 15), max_size=400))
def test_range_coder(symbols):
    assert codecs.range_decode(codecs.range_encode(symbols, 16), len(symbols), 16) == symbols


def test_strip_is_the_best_line():
    rng = np.random.default_rng(5)
    for n in (3, 5, 9):
        t, v = np.arange(n), rng.normal(size=n)
        slopes = np.linspace(-8, 8, 20001)
        best = min(np.ptp(v - s * t) / 2 for s in slopes)
        assert abs(codecs.strip(t, v) - best) < 2e-3
