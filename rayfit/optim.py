"""Gradient descent, nonlinear conjugate gradients and limited-memory BFGS, each with either line search."""

from __future__ import annotations

import time
from dataclasses import dataclass, field

import numpy as np

from . import wolfe
from .taylor import TaylorModel, taylor_line_search

RESTART = {"taylor": 0.2, "wolfe": 1.0}
TRACE = "run string, dataset string, method string, search string, k int, loss double, grad_norm double, acc double, alpha double, n_eval int, restarts int, fallbacks int, guards int, seconds double, cum_seconds double"
OPS = "run string, i int, op string, seconds double, doubles_reduced long, doubles_broadcast long, warm boolean"


@dataclass
class Fit:
    w: np.ndarray
    trace: list[dict]
    ops: list
    status: str
    state: dict = field(default_factory=dict)

    def trace_rows(self, run: str = "", dataset: str = "") -> list[tuple]:
        return [(run, dataset, t["method"], t["search"], t["k"], t["loss"], t["grad_norm"], float(np.exp(-t["loss"])), t["alpha"], t["n_eval"], t["restarts"], t["fallbacks"], t["guards"], t["seconds"], t["cum_seconds"]) for t in self.trace]

    def ops_rows(self, run: str = "") -> list[tuple]:
        return [(run, i, o.op, o.seconds, o.reduced, o.broadcast, o.warm) for i, o in enumerate(self.ops)]

    def trace_frame(self, spark, run: str = "", dataset: str = ""):
        return spark.createDataFrame(self.trace_rows(run, dataset), TRACE)

    def ops_frame(self, spark, run: str = ""):
        return spark.createDataFrame(self.ops_rows(run), OPS)


def unit(p: np.ndarray) -> np.ndarray:
    n = np.linalg.norm(p)
    return p / n if n else p


def initial_step(policy: str, k: int, alpha: float, slope_before: float, slope: float) -> float:
    """one: always 1. slope_ratio: the step before, scaled by how much steeper the ray was then; 1 at first."""
    return 1.0 if policy == "one" or k == 0 or slope == 0 else alpha * slope_before / slope


class Gd:
    policy = "slope_ratio"

    def direction(self, g):
        return -g, 0

    def moved(self, s, y):
        pass


class Ncg:
    """Polak-Ribiere, never negative, restarted where consecutive gradients are far from orthogonal."""

    policy = "slope_ratio"

    def __init__(self, restart: float, scale: np.ndarray | None = None):
        self.restart, self.scale, self.g, self.p = restart, scale, None, None

    def direction(self, g):
        h = g if self.scale is None else g / self.scale
        fresh = 0
        if self.g is None:
            p = -h
        else:
            fresh = int(abs(h @ self.g) >= self.restart * (g @ h))
            before = self.g if self.scale is None else self.g / self.scale
            beta = 0.0 if fresh else max(0.0, (h @ (g - self.g)) / (self.g @ before))
            p = -h + beta * self.p
        self.g, self.p = g, p
        return p, fresh

    def reset(self, g):
        self.p = -g
        return self.p

    def moved(self, s, y):
        pass


class Lbfgs:
    policy = "one"

    def __init__(self, history: int = 5):
        self.h, self.pairs = history, []

    def direction(self, g):
        q, held = g.copy(), []
        for s, y in reversed(self.pairs):
            a = (s @ q) / (s @ y)
            held.append(a)
            q -= a * y
        if self.pairs:
            s, y = self.pairs[-1]
            q *= (s @ y) / (y @ y)
        for (s, y), a in zip(self.pairs, reversed(held), strict=True):
            q += (a - (y @ q) / (s @ y)) * s
        return -q, 0

    def moved(self, s, y):
        if s @ y > 1e-16 * (y @ y):
            self.pairs = [*self.pairs, (s, y)][-self.h :]


def two_loop_dots(gram: np.ndarray, pairs: int) -> np.ndarray:
    """The two loops on dot products alone: coefficients of the direction in the basis s_1..s_h, y_1..y_h, g.

    gram holds all dot products of that basis, so vectors may stay in tables; see tables.two_loop."""
    h, d = pairs, np.zeros(2 * pairs + 1)
    d[-1] = 1.0
    held = np.zeros(h)
    for i in range(h - 1, -1, -1):
        held[i] = (gram[i] @ d) / gram[i, h + i]
        d[h + i] -= held[i]
    if h:
        d *= gram[h - 1, 2 * h - 1] / gram[2 * h - 1, 2 * h - 1]
    for i in range(h):
        d[i] += held[i] - (gram[h + i] @ d) / gram[i, h + i]
    return -d


def newton_cg(problem, w, g, steps: int = 10):
    """A truncated Newton direction: conjugate gradients on products with the second derivative, one pass each."""
    p, r = np.zeros_like(g), -g
    d, rr = r.copy(), r @ r
    tol = min(0.5, np.sqrt(np.linalg.norm(g))) * np.linalg.norm(g)
    for _ in range(steps):
        hd = problem.curvature_product(w, d)
        bend = d @ hd
        if bend <= 1e-16 * (d @ d):
            break
        a = rr / bend
        p, r = p + a * d, r - a * hd
        after = r @ r
        if np.sqrt(after) <= tol:
            break
        d, rr = r + after / rr * d, after
    return p if p.any() else -g


def diagonal(problem, w) -> np.ndarray:
    """The second derivative's diagonal at w by one product, with the vector of ones: exact where features do not share
    rows, otherwise their row sums; positive for the losses here if features are nonnegative. For ncg(precondition)."""
    d = np.abs(problem.curvature_product(w, np.ones(problem.m)))
    return np.maximum(d, 1e-8 * max(1e-300, float(d.max())))


def stop_rule(max_iter: int, grad_tol: float = 1e-10, rel_loss: float = 1e-15, plateau: int = 2, acc_gain: float = 0.0, acc_span: int = 5):
    """True once iterations run out, the gradient is small, the loss has not moved for plateau iterations, or exp(-loss) has
    gained less than acc_gain over the last acc_span iterations (never, with acc_gain 0)."""
    still, accs = [0], []

    def test(k, grad_norm, before, loss):
        still[0] = still[0] + 1 if before is not None and abs(before - loss) <= rel_loss * abs(loss) else 0
        accs.append(float(np.exp(-loss)))
        flat = len(accs) > acc_span and accs[-1] - accs[-1 - acc_span] < acc_gain
        return k >= max_iter or grad_norm <= grad_tol or still[0] >= plateau or flat

    return test


def minimize(problem, method: str = "lbfgs", search: str = "taylor", w0=None, max_iter: int = 100, degree: int = 5, theta: float = 1e-4, nu1: float = wolfe.NU1, nu2: float = wolfe.NU2, history: int = 5, restart: float | None = None, normalize: bool | None = None, safeguard: bool = True, grad_tol: float = 1e-10, shrink: str = "bisect", argmin: str = "newton", precondition=None, state: dict | None = None, on_iteration=None, deadline: float | None = None, acc_gain: float = 0.0) -> Fit:
    """Minimises problem.value_and_gradient from w0 (zeros), recording a trace row for each iterate.

    search: taylor, wolfe, backtracking or fixed. The recurrences see the raw direction, the searches the unit one where
    normalize is on (gd and ncg with Taylor models). safeguard: a Taylor step that fails to lower the loss is halved,
    which costs nothing unless it happens, as the gradient pass at the new point yields the loss. acc_gain: see stop_rule.
    deadline: seconds after which no further iteration begins; such a fit depends on the clock."""
    w = np.zeros(problem.m) if w0 is None else np.array(w0, float)
    normalize = (method != "lbfgs" and search == "taylor") if normalize is None else normalize
    rule = {"gd": Gd, "lbfgs": lambda: Lbfgs(history), "ncg": lambda: Ncg(RESTART.get(search, 1.0) if restart is None else restart, precondition), "newton": Gd}[method]()
    if state:
        w, rule = state["w"], state["rule"]
    began = time.perf_counter()
    f, g = problem.value_and_gradient(w)
    stop = stop_rule(max_iter, grad_tol, acc_gain=acc_gain)
    trace, alpha, slope_before, before, status = [], 1.0, 0.0, None, "max_iter"
    row = dict(method=method, search=search, alpha=0.0, n_eval=0, restarts=0, fallbacks=0, guards=0, seconds=0.0)
    k = 0
    while True:
        trace.append(row | dict(k=k, loss=f, grad_norm=float(np.linalg.norm(g)), cum_seconds=time.perf_counter() - began))
        if on_iteration:
            on_iteration(k, w, rule, trace[-1])
        if stop(k, trace[-1]["grad_norm"], before, f) or not np.isfinite(f):
            status = "stopped"
            break
        if deadline and time.perf_counter() - began > deadline:
            status = "deadline"
            break
        start = time.perf_counter()
        if method == "newton":
            p, restarted = newton_cg(problem, w, g), 0
        else:
            p, restarted = rule.direction(g)
        if g @ p >= 0:
            p, restarted = (rule.reset(g) if method == "ncg" else -g), restarted + 1
            if method == "lbfgs":
                rule.pairs = []
        ray = unit(p) if normalize else p
        slope = float(g @ ray)
        alpha0 = initial_step("one" if method == "newton" else rule.policy, k, alpha, slope_before, slope)
        if search == "taylor":
            problem.begin_ray(w, ray)
            step = taylor_line_search(lambda a: problem.coefficients(w, ray, a, degree), alpha0, theta, method=argmin)
            problem.end_ray()
            for _ in range(40 if safeguard else 1):
                f2, g2 = problem.value_and_gradient(w + step.alpha * ray, with_value=False)
                if not safeguard or f2 <= f + nu1 * step.alpha * slope + 1e-14 * abs(f):
                    break
                step.alpha, step.guards = step.alpha / 2, step.guards + 1
            else:
                status = "no_decrease"
                break
        else:
            def evaluate(a):
                value, grad = problem.value_and_gradient(w + a * ray)
                return value, float(grad @ ray), grad

            own = {"wolfe": lambda: wolfe.line_search(evaluate, f, slope, alpha0, nu1, nu2, shrink), "backtracking": lambda: wolfe.backtracking(evaluate, f, slope, alpha0), "fixed": lambda: wolfe.fixed_step(evaluate, f, slope, alpha0)}
            step = own[search]()
            if step.gradient is None:
                status = "no_step"
                break
            f2, g2 = step.value, step.gradient
        s = step.alpha * ray
        rule.moved(s, g2 - g)
        w, before, f, g, alpha, slope_before = w + s, f, f2, g2, step.alpha, slope
        k += 1
        row = dict(method=method, search=search, alpha=step.alpha, n_eval=step.n_eval, restarts=restarted, fallbacks=step.fallbacks, guards=step.guards, seconds=time.perf_counter() - start)
    return Fit(w, trace, problem.ops, status, {"w": w, "rule": rule})


class ArrayProblem:
    """The same interface on arrays in memory: x (n x m), y. For tests and for one-machine comparisons."""

    def __init__(self, x, y, loss, lam=0.0):
        from .losses import L2

        self.x, self.y, self.loss, self.penalty, self.m, self.ops = x, y, loss, L2(lam), x.shape[1], []

    def value_and_gradient(self, w, with_value=True):
        b = self.loss.kernel(self.x @ w, np.ones(len(self.y)), self.y, 1)
        return b[0].mean() + self.penalty.value(w), b[1] @ self.x / len(self.y) + self.penalty.gradient(w)

    def gradient(self, w):
        return self.value_and_gradient(w)[1]

    def curvature_product(self, w, d):
        bend = 2 * self.loss.kernel(self.x @ w, np.ones(len(self.y)), self.y, 2)[2]
        return (bend * (self.x @ d)) @ self.x / len(self.y) + self.penalty.gradient(d)

    def begin_ray(self, w, p):
        pass

    def end_ray(self):
        pass

    def coefficients(self, w, p, alpha, degree):
        r = w + alpha * p
        c = self.loss.kernel(self.x @ r, self.x @ p, self.y, degree).mean(1)
        return TaylorModel(c + self.penalty.terms(r, p, degree), alpha, self.loss.exact_degree is not None and degree >= max(2, self.loss.exact_degree))


def mllib_reference(data, lam: float, max_iter: int = 100):
    """The library's own L-BFGS on the same objective: weights (the constant feature is one of them) and losses."""
    from pyspark.ml.classification import LogisticRegression
    from pyspark.ml.functions import array_to_vector
    from pyspark.sql import functions as F

    if data.kind == "sparse":
        from pyspark.ml.linalg import SparseVector, VectorUDT

        # Spark has no built-in function from pairs to the library's sparse vectors
        to = F.udf(lambda i, v, m=data.m: SparseVector(m, i, v), VectorUDT())
        features = to("idx", "val")
    else:
        x = F.array(*data.features) if data.kind == "narrow" else F.col("x")
        features = array_to_vector(x.cast("array<double>"))
    df = data.df.select(features.alias("features"), (F.col("y") != 0).cast("double").alias("label"))
    fit = LogisticRegression(regParam=lam, elasticNetParam=0.0, standardization=False, fitIntercept=False, maxIter=max_iter, tol=1e-12).fit(df)
    return fit.coefficients.toArray(), list(fit.summary.objectiveHistory)
