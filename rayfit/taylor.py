"""The polynomial model of a loss along a ray, and the line search that rests on it."""

from __future__ import annotations

import math
from collections.abc import Callable, Sequence
from dataclasses import dataclass, field

import numpy as np

TINY = 1e-300


@dataclass(frozen=True)
class Argmin:
    t: float
    status: str  # newton, fallback, bisect, backtrack, roots, flat


class TaylorModel:
    """W(t) = sum c_k t^k, an approximation of the loss at alpha + t."""

    def __init__(self, coeffs: Sequence[float], alpha: float = 0.0, exact: bool = False):
        self.c, self.alpha, self.exact = [float(x) for x in coeffs], float(alpha), exact

    @property
    def degree(self) -> int:
        return len(self.c) - 1

    def _horner(self, c: Sequence[float], t: float) -> float:
        out = 0.0
        for x in reversed(c):
            out = out * t + x
        return out

    def value(self, t: float) -> float:
        return self._horner(self.c, t)

    def d1(self, t: float) -> float:
        return self._horner([k * x for k, x in enumerate(self.c)][1:], t)

    def d2(self, t: float) -> float:
        return self._horner([k * (k - 1) * x for k, x in enumerate(self.c)][2:], t)

    def fallback(self) -> float:
        """The step of the quadratic part; infinite where it does not curve upwards."""
        return -self.c[1] / (2 * self.c[2]) if self.degree >= 2 and self.c[2] > 0 else math.inf

    def _settled(self, t: float, tol: float, strict: bool) -> bool:
        size = 1.0 if strict else max(1.0, sum(k * abs(x) * abs(t) ** (k - 1) for k, x in enumerate(self.c) if k))
        return abs(self.d1(t)) <= tol * size

    def acceptable(self, t: float) -> bool:
        """A minimum, ahead of the start of the ray, that does not raise the model."""
        return math.isfinite(t) and self.alpha + t > 0 and self.d2(t) > 0 and self.value(t) <= self.c[0] + 1e-14 * abs(self.c[0])

    def argmin(self, method: str = "newton", max_iter: int = 10, tol: float = 1e-15, strict_tol: bool = False) -> Argmin:
        """A minimiser of the model by the method, or else the quadratic step."""
        found = getattr(self, f"_{method}")(max_iter, tol, strict_tol)
        if found is not None and self.acceptable(found):
            return Argmin(found, method)
        return Argmin(self.fallback(), "fallback")

    def _newton(self, max_iter, tol, strict):
        t = 0.0
        for _ in range(max_iter):
            if self._settled(t, tol, strict):
                return t
            bend = self.d2(t)
            if bend == 0 or not math.isfinite(bend):
                return None
            after = t - self.d1(t) / bend
            if not math.isfinite(after):
                return None
            if after == t and not strict:
                return t
            t = after
        return t if self._settled(t, tol, strict) else None

    def _bracket(self):
        low, step = (0.0, 1.0) if self.d1(0.0) < 0 else (0.0, -1.0)
        for _ in range(60):
            high = low + step
            if not math.isfinite(self.d1(high)):
                return None
            if (self.d1(high) >= 0) == (step > 0):
                return (low, high) if step > 0 else (high, low)
            low, step = high, 2 * step
        return None

    def _bisect(self, max_iter, tol, strict):
        ends = self._bracket()
        if ends is None:
            return None
        a, b = ends
        for _ in range(max(200, max_iter)):
            m = (a + b) / 2
            if m in (a, b):
                break
            a, b = (m, b) if self.d1(m) < 0 else (a, m)
        return (a + b) / 2

    def _backtrack(self, max_iter, tol, strict):
        t = self.fallback()
        if not math.isfinite(t):
            return None
        for _ in range(max(60, max_iter)):
            if self.value(t) <= self.c[0] + 1e-4 * t * self.c[1]:
                return t
            t /= 2
        return None

    def _roots(self, max_iter, tol, strict):
        slope = [k * x for k, x in enumerate(self.c)][1:]
        while slope and slope[-1] == 0:
            slope.pop()
        real = [float(r.real) for r in np.roots(slope[::-1]) if abs(r.imag) <= 1e-9 * max(1.0, abs(r))] if len(slope) > 1 else []
        return min((r for r in real if self.acceptable(r)), key=self.value, default=None)

    def error_estimate(self, t: float) -> float:
        """The last term, as a stand-in for those left out; nothing is left out of an exact model."""
        return 0.0 if self.exact else self.c[-1] * t**self.degree

    def trusted(self, t: float, theta: float) -> bool:
        return self.exact or abs(self.error_estimate(t)) <= theta * max(abs(self.value(t)), TINY)


@dataclass
class Step:
    alpha: float
    n_eval: int
    history: list = field(default_factory=list)  # (alpha, coefficients, t, error estimate, status) or (alpha, value, slope)
    value: float | None = None
    gradient: object = None
    fallbacks: int = 0
    guards: int = 0


def taylor_line_search(expand: Callable[[float], TaylorModel], alpha0: float = 1.0, theta: float = 1e-4, max_expansions: int = 10, method: str = "newton", growth: float = 10.0, strict_tol: bool = False) -> Step:
    """Expands at alpha0, moves to the model's minimum, and expands again there until the model is trusted at its minimum.

    expand(alpha) costs one pass. Guards: a point at or behind the start halves alpha, and a step grows it by growth at most."""
    alpha, step = float(alpha0), Step(float(alpha0), 0)
    for _ in range(max_expansions):
        model = expand(alpha)
        step.n_eval += 1
        best = model.argmin(method, strict_tol=strict_tol)
        step.fallbacks += best.status == "fallback"
        t = best.t
        if not math.isfinite(t) and model.c[1] < 0:
            t = (growth - 1) * alpha  # downhill without a minimum in sight
        if not math.isfinite(t) or alpha + t <= 0:
            t = -alpha / 2
            step.guards += 1
        elif alpha + t > growth * alpha:
            t = (growth - 1) * alpha
            step.guards += 1
        step.history.append((alpha, list(model.c), t, model.error_estimate(t), best.status))
        clipped = t != best.t
        alpha += t
        if not clipped and (model.trusted(t, theta) or abs(t) <= 1e-12 * max(1.0, alpha)):
            break
    step.alpha = alpha
    return step


def exact_line_search(expand, alpha0: float = 1.0) -> Step:
    """To high accuracy; the reference for how good a step is."""
    return taylor_line_search(expand, alpha0, theta=1e-14, max_expansions=30)


def scalar_expand(derivatives: Callable[[float, int], float], degree: int) -> Callable[[float], TaylorModel]:
    """expand() of a function of one number, given its derivatives f(x, order)."""
    return lambda a: TaylorModel([derivatives(a, k) / math.factorial(k) for k in range(degree + 1)], a)


def worked_example(alpha: float, order: int) -> float:
    """Derivatives of alpha e^alpha + e^(4 - alpha)."""
    return (alpha + order) * math.exp(alpha) + (-1) ** order * math.exp(4 - alpha)
