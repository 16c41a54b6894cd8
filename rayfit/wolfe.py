"""The baseline: a bracketing search by cubic interpolation for the strong Wolfe conditions, and plainer ones."""

from __future__ import annotations

import math
from collections.abc import Callable

from .taylor import Step

NU1, NU2 = 1e-4, 0.9
#: evaluate(alpha) returns (value, slope along the ray, whatever the caller wants back for the accepted point).
Evaluate = Callable[[float], tuple[float, float, object]]


def decrease(phi: float, phi0: float, dphi0: float, a: float, nu1: float = NU1) -> bool:
    return phi <= phi0 + nu1 * a * dphi0


def curvature(dphi: float, dphi0: float, nu2: float = NU2) -> bool:
    return abs(dphi) <= nu2 * abs(dphi0)


def cubic_min(a: float, fa: float, da: float, b: float, fb: float, db: float) -> float:
    """Where the cubic with these values and slopes at a and b is least; nan if it has no minimum."""
    e = da + db - 3 * (fb - fa) / (b - a)
    inside = e * e - da * db
    if inside < 0:
        return math.nan
    root = math.copysign(math.sqrt(inside), b - a)
    below = db - da + 2 * root
    return b - (b - a) * (db + root - e) / below if below else math.nan


def line_search(evaluate: Evaluate, phi0: float, dphi0: float, alpha0: float = 1.0, nu1: float = NU1, nu2: float = NU2, shrink: str = "bisect", max_eval: int = 25) -> Step:
    """Takes alpha0 untouched if both conditions hold there; else brackets by doubling and shrinks by cubic steps.

    shrink says what replaces a cubic point at the edge of the bracket: its middle (bisect), the secant of the slopes
    (secant), or the value-only parabola averaged with the secant (dual)."""
    step = Step(0.0, 0)
    low, high = (0.0, phi0, dphi0), None
    a = float(alpha0)
    best = None
    while step.n_eval < max_eval:
        f, d, held = evaluate(a)
        step.n_eval += 1
        step.history.append((a, f, d))
        fine = math.isfinite(f) and math.isfinite(d)
        down = fine and decrease(f, phi0, dphi0, a, nu1)
        if down and (best is None or f < best[1]):
            best = (a, f, held)
        if down and curvature(d, dphi0, nu2):
            best = (a, f, held)
            break
        here = (a, f, d)
        if not fine:
            high = (a, math.inf, math.inf)
        elif not down or f >= low[1]:
            high = here
        elif d * ((high[0] if high else math.inf) - a) >= 0:
            high, low = low, here
            if high[0] > low[0]:
                high, low = low, high
        else:
            low = here
        if high is None:
            a *= 2
            continue
        left, right = sorted((low, high), key=lambda x: x[0])
        width = right[0] - left[0]
        if width <= 1e-14 * max(1.0, right[0]):
            break
        middle = left[0] + width / 2
        a = cubic_min(*left, *right) if math.isfinite(right[1]) and math.isfinite(right[2]) else math.nan
        if not left[0] + 0.1 * width < a < right[0] - 0.1 * width:
            secant = left[0] - left[2] * width / (right[2] - left[2]) if math.isfinite(right[2]) and right[2] != left[2] else math.nan
            bend = right[1] - left[1] - left[2] * width
            dual = (left[0] - left[2] * width**2 / (2 * bend) + secant) / 2 if bend else math.nan
            a = {"bisect": middle, "secant": secant, "dual": dual}[shrink]
            if not left[0] + 0.1 * width < a < right[0] - 0.1 * width:
                a = middle
    if best is not None:
        step.alpha, step.value, step.gradient = best
    return step


def fixed_step(evaluate: Evaluate, phi0: float, dphi0: float, alpha0: float = 1.0) -> Step:
    f, d, held = evaluate(alpha0)
    return Step(alpha0, 1, [(alpha0, f, d)], f, held)


def backtracking(evaluate: Evaluate, phi0: float, dphi0: float, alpha0: float = 1.0, shrink: float = 0.5, nu1: float = NU1, max_eval: int = 40) -> Step:
    step, a = Step(0.0, 0), alpha0
    for _ in range(max_eval):
        f, d, held = evaluate(a)
        step.n_eval += 1
        step.history.append((a, f, d))
        if math.isfinite(f) and decrease(f, phi0, dphi0, a, nu1):
            step.alpha, step.value, step.gradient = a, f, held
            break
        a *= shrink
    return step
