"""Image preparation on flat float arrays (x fastest, then y, then z): column expressions for single steps, numpy for whole pipelines at scale."""

from __future__ import annotations

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .portable import permille


def is_volume(nz: Column, threshold: int = 40) -> Column:
    return nz >= threshold


def normalise(a: Column, lo: float = 0.0, hi: float = 1.0) -> Column:
    """Min-max to [lo, hi]; a constant image becomes lo."""
    least, span = F.array_min(a), F.array_max(a) - F.array_min(a)
    return F.transform(a, lambda v: F.when(span > 0, F.lit(lo) + (v - least) / span * (hi - lo)).otherwise(F.lit(lo)))


def to_grey(channels: Column) -> Column:
    """Mean of the channels, pixel by pixel."""
    first = F.transform(F.get(channels, F.lit(0)), lambda v: v * 0.0)
    return F.transform(F.aggregate(channels, first, lambda acc, c: F.zip_with(acc, c, lambda p, q: p + q)), lambda v: v / F.size(channels))


def projection(a: Column, nx: int, ny: int, nz: int, axis: str) -> Column:
    """Maximum-intensity projection along an axis, as a flat array of the other two (the faster one first)."""
    strides = {"x": (1, nx, ny * nz, lambda k: k * nx), "y": (nx, ny, nx * nz, lambda k: k % nx + F.floor(k / nx).cast("int") * (nx * ny)), "z": (nx * ny, nz, nx * ny, lambda k: k)}
    step, n, cells, at = strides[axis]
    return F.transform(F.sequence(F.lit(0), F.lit(cells - 1)), lambda k: F.array_max(F.transform(F.sequence(F.lit(0), F.lit(n - 1)), lambda i: F.get(a, at(k) + i * step))))


def slices(a: Column, nx: int, ny: int, nz: int) -> Column:
    """First, middle and last slice as three channels."""
    return F.array(*(F.slice(a, z * nx * ny + 1, nx * ny) for z in (0, nz // 2, nz - 1)))


def resample_linear(a: Column, nx: int, ny: int, mx: int, my: int) -> Column:
    """Bilinear, corners on corners."""
    def cell(k):
        px, py = (k % mx) * ((nx - 1) / (mx - 1)), F.floor(k / mx) * ((ny - 1) / (my - 1))
        x0, y0 = F.least(F.floor(px), F.lit(nx - 2)), F.least(F.floor(py), F.lit(ny - 2))
        fx, fy = px - x0, py - y0
        p = lambda x, y: F.get(a, (y * nx + x).cast("int"))
        return (p(x0, y0) * (1 - fx) + p(x0 + 1, y0) * fx) * (1 - fy) + (p(x0, y0 + 1) * (1 - fx) + p(x0 + 1, y0 + 1) * fx) * fy

    return F.transform(F.sequence(F.lit(0), F.lit(mx * my - 1)), cell)


def flip_rows(a: Column, nx: int, ny: int) -> Column:
    return F.flatten(F.transform(F.sequence(F.lit(0), F.lit(ny - 1)), lambda y: F.reverse(F.slice(a, y * nx + 1, F.lit(nx)))))


def rotate(a: Column, n: int) -> Column:
    """A square image by a quarter turn."""
    return F.transform(F.sequence(F.lit(0), F.lit(n * n - 1)), lambda k: F.get(a, ((k % n) * n + (n - 1 - F.floor(k / n))).cast("int")))


def augment(df: DataFrame, key: str, data: str, n: int, p: float = 0.2, seed: int = 51) -> DataFrame:
    """Each image is flipped with probability p and turned with probability p, by portable draws on its key."""
    flip, turn = (F.expr(f"{permille(key, seed + i)} < {int(1000 * p)}") for i in range(2))
    x = df.withColumn(data, F.when(flip, flip_rows(F.col(data), n, n)).otherwise(F.col(data)))
    return x.withColumn(data, F.when(turn, rotate(F.col(data), n)).otherwise(F.col(data)))


def stretch(a: Column, lo: int, hi: int) -> Column:
    """Contrast: the lo-th and hi-th smallest values (from 1) become 0 and 1, what lies beyond is clipped."""
    s = F.array_sort(a)
    low, high = F.element_at(s, lo), F.element_at(s, hi)
    return F.transform(a, lambda v: F.when(high > low, F.greatest(F.lit(0.0), F.least(F.lit(1.0), (v - low) / (high - low)))).otherwise(F.lit(0.0)))


def crop(a: Column, nx: int, x0: int, y0: int, mx: int, my: int) -> Column:
    return F.flatten(F.array(*(F.slice(a, (y0 + y) * nx + x0 + 1, mx) for y in range(my))))


def spline_matrix(n: int, m: int, order: int = 3) -> np.ndarray:
    """Weights (m, n) of not-a-knot cubic (or linear) spline interpolation at m points, corners on corners: reproduces cubics, identity for m = n."""
    x, at = np.arange(n, dtype=float), np.linspace(0, n - 1, m)
    i = np.clip(np.floor(at).astype(int), 0, max(n - 2, 0))
    f = at - i
    if n == 1:
        return np.ones((m, 1))
    if order == 1 or n < 4:
        w = np.zeros((m, n))
        w[np.arange(m), i] = 1 - f
        w[np.arange(m), i + 1] += f
        return w
    # Second derivatives s solve A s = B y: continuity inside, equal third derivatives at the last inner knots.
    a, b = np.zeros((n, n)), np.zeros((n, n))
    for k in range(1, n - 1):
        a[k, k - 1 : k + 2] = 1, 4, 1
        b[k, k - 1 : k + 2] = 6, -12, 6
    a[0, :3], a[-1, -3:] = (1, -2, 1), (1, -2, 1)
    s = np.linalg.solve(a, b)
    e = np.eye(n)
    return (1 - f)[:, None] * e[i] + f[:, None] * e[i + 1] + ((1 - f) ** 3 - (1 - f))[:, None] / 6 * s[i] + (f**3 - f)[:, None] / 6 * s[i + 1]


def prepare(pixels: DataFrame, size: int, z_threshold: int = 40, order: int = 3) -> DataFrame:
    """(key, nx, ny, nz, data) -> (key, channels): normalised, resampled to size; volumes by three projections, stacks by first, middle and last slice."""
    def run(batches):
        for b in batches:
            out = []
            for nx, ny, nz, data in zip(b["nx"], b["ny"], b["nz"], b["data"]):
                v = np.asarray(data, float).reshape(nz, ny, nx)
                span = v.max() - v.min()
                v = (v - v.min()) / span if span > 0 else np.zeros_like(v)
                v = np.einsum("ay,bx,zyx->zab", spline_matrix(ny, size, order), spline_matrix(nx, size, order), v)
                if nz >= z_threshold:
                    v = np.einsum("az,zyx->ayx", spline_matrix(nz, size, order), v)
                    three = [v.max(0), v.max(1), v.max(2)]
                else:
                    three = [v[0], v[nz // 2], v[nz - 1]]
                out.append([c.reshape(-1).tolist() for c in three])
            yield pd.DataFrame({"key": b["key"], "channels": out})

    return pixels.select("key", "nx", "ny", "nz", "data").mapInPandas(run, "key long, channels array<array<double>>")
