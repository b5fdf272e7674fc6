"""First-order methods on a distributed matrix; each step takes one forward and one transposed product.

Short vectors, m values, are arrays on the driver. Long vectors stay on the cluster in the overlapped layout and are written
anew every few steps to cut their lineage.
"""

from __future__ import annotations

from dataclasses import dataclass, field

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from nzspan.session import discard, written

from . import vectors
from .layout import Distributed, place
from .products import dense, forward, normal, pack_columns, short_frame, transposed


@dataclass
class Trace:
    """A solver's result: x (long, or short for the eigenvector), and a value for each iteration."""

    x: DataFrame | np.ndarray | None = None
    values: list[float] = field(default_factory=list)
    residuals: list[float] = field(default_factory=list)
    tol: float = 0.0

    def frame(self, spark) -> DataFrame:
        """(iteration, value, residual, reached): reached tells whether the residual met the tolerance by then."""
        rows = [(i, float(v), float(r), bool(r <= self.tol)) for i, (v, r) in enumerate(zip(self.values, self.residuals, strict=True))]
        return spark.createDataFrame(rows, "iteration int, value double, residual double, reached boolean")


class Pair:
    """Products of one matrix with arrays on the short side."""

    def __init__(self, d: Distributed):
        self.d, self.spark = d, d.placed.sparkSession

    def forward(self, x: DataFrame) -> np.ndarray:
        return dense(forward(self.d, x), "row", "y", self.d.matrix.m)

    def transposed(self, v: np.ndarray) -> DataFrame:
        return transposed(self.d, short_frame(self.spark, v)).withColumnRenamed("u", "x")

    def normal(self, w: np.ndarray) -> np.ndarray:
        """A times A transposed times w."""
        if self.d.packed is None:
            self.d.packed = pack_columns(self.d).persist()
        return normal(self.d, self.d.packed, w)


def conjugate_gradient(d: Distributed, b: np.ndarray, ridge: float = 1.0, tol: float = 1e-8, max_iter: int = 50) -> Trace:
    """x = Aᵀ w with (A Aᵀ + ridge I) w = b: the ridge solution of A x = b. residual: relative, of w's system; value: half the squared misfit with the ridge."""
    pair = Pair(d)
    w, r = np.zeros(len(b)), b.astype(float).copy()
    p, rr, scale, out = r.copy(), float(r @ r), max(float(b @ b), 1e-300) ** 0.5, Trace(tol=tol)
    while len(out.values) < max_iter and rr**0.5 / scale > tol:
        q = pair.normal(p) + ridge * p
        alpha = rr / float(p @ q)
        w, r = w + alpha * p, r - alpha * q
        new = float(r @ r)
        p, rr = r + new / rr * p, new
        # with s = A Aᵀ w = b - r - ridge w, the misfit is s - b and the ridge term w · s
        s = b - r - ridge * w
        out.values.append(0.5 * float((s - b) @ (s - b)) + 0.5 * ridge * float(w @ s))
        out.residuals.append(rr**0.5 / scale)
    out.x = pair.transposed(w)
    return out


def spectral_gradient(
    d: Distributed, b: np.ndarray, ridge: float = 1.0, memory: int = 5, tol: float = 1e-6, max_iter: int = 50, lo: float | None = None, hi: float | None = None, first_step: float | None = None
) -> Trace:
    """Least ½‖A x − b‖² + ½ ridge ‖x‖² by gradient steps of spectral length, on a box if lo or hi is given.

    The step is ⟨s, s⟩ / ⟨s, y⟩ of the last moves s of x and y of the gradient. A step is halved until the value is below the largest
    of the last `memory` ones by a part of the decrease that the gradient promises. residual: norm of the projected gradient, relative to the first.
    """
    pair, out = Pair(d), Trace(tol=tol)
    tables: dict[int, DataFrame] = {}

    def kept(df: DataFrame) -> DataFrame:
        """df, written and placed anew: a checkpoint would hand what is known of its columns on to the next, and that doubles in each step."""
        table = written(df.select("part", "col", "x", "is_home"), "long")
        out = place(table, d.n_parts)
        tables[id(out)] = table
        return out

    def drop(*old: DataFrame) -> None:
        discard(*[tables.pop(id(df)) for df in old if id(df) in tables])

    def clip(x: DataFrame) -> DataFrame:
        if lo is None and hi is None:
            return x
        value = F.col("x")
        value = value if lo is None else F.greatest(value, F.lit(float(lo)))
        return x.withColumn("x", value if hi is None else F.least(value, F.lit(float(hi))))

    def one(df: DataFrame, column: str) -> float:
        return float(df.first()[column] or 0.0)

    def gradient(x: DataFrame, misfit: np.ndarray) -> DataFrame:
        return kept(vectors.axpy(ridge, x, pair.transposed(misfit)))

    def value(x: DataFrame, misfit: np.ndarray) -> float:
        return 0.5 * float(misfit @ misfit) + 0.5 * ridge * one(vectors.norm2(x), "norm2")

    x = kept(clip(vectors.scale(0.0, pair.transposed(np.ones(d.matrix.m)))))
    misfit = pair.forward(x) - b
    g, f = gradient(x, misfit), value(x, misfit)
    step = first_step or 1.0 / max(one(vectors.norm2(g), "norm2") ** 0.5, 1e-300)
    history, start = [f], None
    while len(out.values) < max_iter:
        move = kept(vectors.axpy(-1.0, x, clip(vectors.axpy(-step, g, x))))  # to the projection of x - step g
        slope = one(vectors.dot(g, move), "dot")
        size = one(vectors.norm2(move), "norm2") ** 0.5 / step
        start = start or max(size, 1e-300)
        if size / start <= tol:
            break
        part, product = 1.0, pair.forward(move)
        while True:
            new_misfit = misfit + part * product
            new_x = kept(vectors.axpy(part, move, x))
            new_f = value(new_x, new_misfit)
            if new_f <= max(history[-memory:]) + 1e-4 * part * slope or part < 1e-6:
                break
            part /= 2
        new_g = gradient(new_x, new_misfit)
        turn = vectors.axpy(-1.0, g, new_g)
        ss, sy = part * part * one(vectors.norm2(move), "norm2"), part * one(vectors.dot(move, turn), "dot")
        step = min(max(ss / sy, 1e-12), 1e12) if sy > 0 else step
        drop(x, g, move)
        x, g, f, misfit = new_x, new_g, new_f, new_misfit
        history.append(f)
        out.values.append(f)
        out.residuals.append(size / start)
    out.x = x
    return out


def projected_spectral_gradient(d: Distributed, b: np.ndarray, lo: float, hi: float, **more) -> Trace:
    return spectral_gradient(d, b, lo=lo, hi=hi, **more)


def largest_singular_value(d: Distributed, iterations: int = 10, seed: int = 42, tol: float = 1e-3) -> Trace:
    """Power iteration on A Aᵀ, until the relative change is at most tol; value: the estimate of the largest singular value, residual: its relative change."""
    pair, out = Pair(d), Trace(tol=tol)
    w = np.random.default_rng(seed).normal(size=d.matrix.m)
    w /= np.linalg.norm(w)
    for _ in range(iterations):
        q = pair.normal(w)
        size = float(np.linalg.norm(q))
        w = q / size if size else w
        before = out.values[-1] if out.values else 0.0
        out.values.append(size**0.5)
        out.residuals.append(abs(size**0.5 - before) / max(size**0.5, 1e-300))
        if out.residuals[-1] <= tol:
            break
    out.x = w
    return out


def gradient_descent(d: Distributed, b: np.ndarray, ridge: float = 1.0, max_iter: int = 20, step: float | None = None) -> Trace:
    """Steps of one fixed length, below 1 / (σ² + ridge) if not given, for comparison. As x starts at 0 it stays Aᵀ w, so that w alone is kept."""
    pair, out = Pair(d), Trace()
    step = step or 0.9 / (largest_singular_value(d, 6).values[-1] ** 2 * 1.1 + ridge)
    w, misfit, product = np.zeros(len(b)), -b.astype(float), np.zeros(len(b))
    for _ in range(max_iter):
        direction = misfit + ridge * w  # the gradient is Aᵀ times this
        image = pair.normal(direction)
        out.residuals.append(float(max(direction @ image, 0.0)) ** 0.5)
        w, product = w - step * direction, product - step * image
        misfit = product - b
        out.values.append(0.5 * float(misfit @ misfit) + 0.5 * ridge * float(w @ product))
    first = out.residuals[0] if out.residuals else 1.0
    out.residuals = [r / max(first, 1e-300) for r in out.residuals]
    out.x = pair.transposed(w)
    return out
