import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

from geopages.operators import codec, cost

EXAMPLES_X = [3, 1, 2, 1, 1, 2, 5, 5, 1, 3, 4, 4, 1, 2, 4, 1, 4, 3, 3, 2, 1, 2, 5, 5, 3, 2, 3, 4, 4, 3, 1, 1, 3, 1]
EDGES = [[], [1.5], [1.5, 2.5], [3.0] * 10, [1.5, -1.5] * 8, [0.0, -0.0], [np.nan, np.inf, -np.inf, 5e-324, -5e-324], list(10 + np.arange(20) * 1e-5), [7.0] * 50 + [1e300] + [7.0] * 50]


def both(v):
    z = codec.codes(codec.to_bits(np.array(v, float)))
    return cost.histogram(z), cost.marker_histogram(z)


def test_widths_of_the_examples():
    h, m = both(EXAMPLES_X)
    assert {i: int(n) for i, n in enumerate(h) if n} == {0: 7, 52: 4, 53: 6, 54: 14, 55: 2}
    assert cost.best_bits(h, m, "paper") == (0, 1664) and cost.best_bits(h, m) == (1, 1697)


def test_known_sizes():
    assert cost.best_bits(*both(10 + np.arange(20) * 1e-5)) == (34, 646)
    assert cost.best_bits(*both([2.0] * 10)) == (0, 0)
    down = np.array([1.0])
    for _ in range(7):
        down = np.r_[down, np.nextafter(down[-1], 0)]
    h, m = both(down)
    assert cost.best_bits(h, m, "paper") == (1, 7) and cost.best_bits(h, m) == (2, 14)
    assert codec.encode_page(np.array([1.5, -1.5] * 8)).tag == codec.RAW


def test_zigzag():
    d = np.array([0, 1, -1, 2, -2], np.int64).view(np.uint64)
    assert codec.zigzag(d).tolist() == [0, 2, 1, 4, 3] and (codec.unzigzag(codec.zigzag(d)) == d).all()


@pytest.mark.parametrize("v", EDGES)
@pytest.mark.parametrize("options", [{}, {"stream": "interleaved"}, {"rle": True}, {"policy": "paper"}, {"min_saving": 0.3}, *[{"policy": "fixed", "fixed_bits": n} for n in (1, 7, 31, 34, 63, 64)]])
def test_edges_round_trip(v, options):
    check(np.array(v, float), options)
    check(np.array(v, float).astype(np.float32), {k: min(32, x) if k == "fixed_bits" else x for k, x in options.items()})


def check(v, options):
    p = codec.encode_page(v, **options)
    w = codec.decode_page(p.tag, p.data, len(v), v.dtype, options.get("stream", "split"))
    assert (codec.to_bits(w) == codec.to_bits(v)).all() and 0 <= 8 * len(p.data) - p.predicted_bits < 8


@settings(max_examples=150, deadline=None)
@given(st.lists(st.integers(0, 2**64 - 1) | st.integers(0, 300), max_size=60), st.sampled_from(["split", "interleaved"]), st.integers(1, 64))
def test_any_bits_round_trip(bits, stream, n):
    v = np.array(bits, np.uint64).view(np.float64)
    check(v, {"stream": stream})
    check(v, {"stream": stream, "policy": "fixed", "fixed_bits": n})
    if len(bits) > 1:
        z = codec.codes(codec.to_bits(v))
        h, m = cost.histogram(z), cost.marker_histogram(z)
        assert (cost.size_two_sums(h) == cost.size_suffix(h)).all() and h.sum() == len(bits) - 1
        best = cost.best_bits(h, m)[1]
        assert all(best <= cost.size_suffix(h)[k] + 64 * m[k] for k in range(1, 65))


def test_bad_pages_raise():
    p = codec.encode_page(10 + np.arange(50) * 1e-5)
    for tag, data, n in ((p.tag, p.data[:20], 50), (9, p.data, 50), (codec.RAW, p.data, 50), (p.tag, b"", 50)):
        with pytest.raises(ValueError):
            codec.decode_page(tag, data, n)
    with pytest.raises(ValueError):
        codec.encode_page(np.arange(5.0), policy="fixed", fixed_bits=0)
