"""Losses: terms of the Taylor model of a row's loss, as Spark columns and as NumPy, from margin z, its slope q and label y."""

from __future__ import annotations

import math
from collections.abc import Callable
from functools import lru_cache

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


@lru_cache
def sigmoid_polynomials(degree: int) -> tuple[tuple[int, ...], ...]:
    """For k = 1..degree, coefficients in s of the k-th derivative of softplus(-z), s = sigmoid(z): s - 1, s - s^2, ..."""
    out: list[list[int]] = [[-1, 1], [0, 1, -1]]
    while len(out) < degree:
        before = out[-1]
        slope = [i * x for i, x in enumerate(before)][1:]
        after = [0] * (len(slope) + 2)
        for i, x in enumerate(slope):
            after[i + 1] += x
            after[i + 2] -= x
        out.append(after)
    return tuple(tuple(x) for x in out[:degree])


def softplus_neg(z: Column) -> Column:
    """log(1 + e^-z) without overflow."""
    return F.log1p(F.exp(-F.abs(z))) + F.greatest(-z, F.lit(0.0))


def sigmoid(z: Column) -> Column:
    return 1 / (1 + F.exp(-z))


def horner(coeffs, x):
    """A polynomial in a column or array from its coefficients, lowest first."""
    out = None
    for c in reversed(list(coeffs)):
        out = F.lit(float(c)) if out is None and isinstance(x, Column) else float(c) if out is None else out * x + float(c)
    return out


class Loss:
    """exact_degree: of the loss along any ray if it is a polynomial, else None."""

    exact_degree: int | None = None

    def value_term(self, z: Column, y: Column) -> Column:
        raise NotImplementedError

    def slope_term(self, z: Column, y: Column) -> Column:
        raise NotImplementedError

    def taylor_terms(self, z: Column, q: Column, y: Column, degree: int) -> list[Column]:
        raise NotImplementedError

    def value(self, z, y):
        return self.kernel(z, np.zeros_like(z), y, 0)[0]

    def slope(self, z, y):
        return self.kernel(z, np.ones_like(z), y, 1)[1]

    def kernel(self, z: np.ndarray, q: np.ndarray, y: np.ndarray, degree: int) -> np.ndarray:
        """(degree + 1) x rows."""
        raise NotImplementedError


class Logistic(Loss):
    """log(1 + e^-z), plus z where the label is 0; any other label counts as 1."""

    def value_term(self, z, y):
        return softplus_neg(z) + F.when(y == 0, z).otherwise(0.0)

    def slope_term(self, z, y):
        return sigmoid(z) - F.when(y == 0, 0.0).otherwise(1.0)

    def taylor_terms(self, z, q, y, degree):
        s, out, power = sigmoid(z), [self.value_term(z, y)], q
        for k, poly in enumerate(sigmoid_polynomials(max(2, degree))[:degree], 1):
            term = self.slope_term(z, y) if k == 1 else horner(poly, s)
            out.append(power * term / float(math.factorial(k)))
            power = power * q
        return out

    def kernel(self, z, q, y, degree):
        zero = (y == 0).astype(float)
        e = np.exp(-np.abs(z))
        s = np.where(z >= 0, 1 / (1 + e), e / (1 + e))
        out = [np.log1p(e) + np.maximum(-z, 0) + zero * z]
        power = q
        for k, poly in enumerate(sigmoid_polynomials(max(2, degree))[:degree], 1):
            out.append(power * (s - 1 + zero if k == 1 else horner(poly, s)) / math.factorial(k))
            power = power * q
        return np.array(out)


class LeastSquares(Loss):
    """Half the squared residual."""

    exact_degree = 2

    def value_term(self, z, y):
        return (z - y) * (z - y) / 2.0

    def slope_term(self, z, y):
        return z - y

    def taylor_terms(self, z, q, y, degree):
        return ([self.value_term(z, y), (z - y) * q, q * q / 2.0] + [F.lit(0.0)] * degree)[: degree + 1]

    def kernel(self, z, q, y, degree):
        e = z - y
        return np.array(([e * e / 2, e * q, q * q / 2] + [np.zeros_like(z)] * degree)[: degree + 1])


class Custom(Loss):
    """From functions of columns or arrays: terms(z, q, y, degree), value(z, y), slope(z, y).

    A check on a few numbers compares the terms with differences of value."""

    def __init__(self, terms: Callable, value: Callable, slope: Callable, exact_degree: int | None = None, check: bool = True):
        self.terms, self._value, self._slope, self.exact_degree = terms, value, slope, exact_degree
        if check:
            z, q, y, h = np.array([-0.7, 0.1, 1.3]), np.array([0.5, -1.0, 0.8]), np.array([0.0, 1.0, 1.0]), 1e-4
            got = self.kernel(z, q, y, 2)
            slope_ = (value(z + h * q, y) - value(z - h * q, y)) / (2 * h)
            bend = (value(z + h * q, y) - 2 * value(z, y) + value(z - h * q, y)) / (2 * h * h)
            if not (np.allclose(got[0], value(z, y)) and np.allclose(got[1], slope_, atol=1e-5) and np.allclose(got[2], bend, atol=1e-4) and np.allclose(slope(z, y) * q, slope_, atol=1e-5)):
                raise ValueError("the terms are not the expansion of the value")

    def value_term(self, z, y):
        return self._value(z, y)

    def slope_term(self, z, y):
        return self._slope(z, y)

    def taylor_terms(self, z, q, y, degree):
        return list(self.terms(z, q, y, degree))

    def kernel(self, z, q, y, degree):
        return np.array([np.broadcast_to(t, z.shape) for t in self.terms(z, q, y, degree)], float)


class L2:
    """lam / 2 times the squared norm; the last parameter is left out if it is a bias that is not to count."""

    def __init__(self, lam: float, regularize_bias: bool = True):
        self.lam, self.bias = float(lam), regularize_bias

    def _cut(self, v):
        return v if self.bias else v[:-1]

    def value(self, w) -> float:
        return self.lam / 2 * float(self._cut(w) @ self._cut(w))

    def gradient(self, w):
        g = self.lam * w
        if not self.bias:
            g[-1] = 0
        return g

    def terms(self, r, p, degree: int) -> np.ndarray:
        """Coefficients in t of the penalty at r + t p."""
        r, p = self._cut(r), self._cut(p)
        out = [self.lam / 2 * float(r @ r), self.lam * float(r @ p), self.lam / 2 * float(p @ p)]
        return np.array((out + [0.0] * degree)[: degree + 1])


class L1:
    def __init__(self, *_):
        raise ValueError("an absolute value is not analytic, so a Taylor model of it says nothing beyond the kink; use L2")
