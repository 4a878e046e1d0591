"""Rounding-error bounds: observed errors never pass them."""

import numpy as np
import pytest

from farpoint.quantize.bounds import FloatFormat, distance_bound, eligible, gamma, quantized_sign, rowwise_bound

KINDS = {16: np.float16, 32: np.float32}


def low_precision(x, y, bits, tree):
    """Squared distances from norms and inner product, every operation rounded to the format."""
    t = KINDS[bits]
    a, b = x.astype(t), y.astype(t)

    def total(v):
        parts = [v[..., k] for k in range(v.shape[-1])]
        if not tree:
            s = parts[0]
            for p in parts[1:]:
                s = (s + p).astype(t)
            return s
        while len(parts) > 1:
            parts = [(parts[k] + parts[k + 1]).astype(t) if k + 1 < len(parts) else parts[k] for k in range(0, len(parts), 2)]
        return parts[0]

    na, nb = total((a * a).astype(t)), total((b * b).astype(t))
    dot = total((a[:, None, :] * b[None]).astype(t))
    return (na[:, None] + nb).astype(t) - (t(2) * dot).astype(t)


@pytest.mark.parametrize("bits", [16, 32])
@pytest.mark.parametrize("d", [1, 2, 3, 7, 64, 300])
@pytest.mark.parametrize("tree", [True, False])
def test_observed_error_is_below_the_bound(bits, d, tree):
    rng = np.random.default_rng(d)
    for make in (lambda: rng.uniform(-1, 1, (20, d)), lambda: np.ones((5, d)), lambda: rng.uniform(0.9, 1, (10, d)), lambda: rng.uniform(-(2.0**-13), 2.0**-13, (10, d))):
        x, y = make(), make()
        exact = ((x[:, None] - y[None]) ** 2).sum(-1)
        error = np.abs(low_precision(x, y, bits, tree).astype(float) - exact)
        top = max(np.abs(x).max(), np.abs(y).max())
        summation = "tree" if tree else "sequential"
        assert (error <= distance_bound(d, top, bits, "sound", summation)).all()
        norms = np.sqrt((x**2).sum(1)), np.sqrt((y**2).sum(1))
        assert (error <= rowwise_bound(*norms, d, top, bits, True, summation)).all()


def test_paper_bound_without_cast_error():
    rng = np.random.default_rng(0)
    x = rng.uniform(-1, 1, (30, 64)).astype(np.float16).astype(float)  # already in the format: no cast error
    error = np.abs(low_precision(x, x, 16, True).astype(float) - ((x[:, None] - x) ** 2).sum(-1))
    assert (error <= distance_bound(64, np.abs(x).max(), 16, "paper")).all()


def test_formats_and_gamma():
    assert FloatFormat(64).eps == 2.0**-53 and FloatFormat(16).top == 65504 and FloatFormat(16).tiny == 2.0**-25
    assert gamma(1, 0.5) == pytest.approx(0.5) and gamma(2, 0.5) == pytest.approx(1.25)
    assert distance_bound(64, 1, 32, "paper") < distance_bound(64, 1, 16, "paper") < distance_bound(64, 1, 16, "sound")


def test_sign_is_exact():
    v = np.array([1e-30, -1e-30, 0.0, -5.0, 1e30, 2.0**-26])
    assert (quantized_sign(v, 16) == np.sign(v)).all()
    assert eligible(False, 2, 1) and not eligible(True, 2, 1) and not eligible(False, 1, 2)
