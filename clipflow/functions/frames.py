"""Columns over a frame that is an array of pixels in row order."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def laplacian_variance(col: str, height: int, width: int) -> Column:
    """Population variance of the five-point Laplacian over interior pixels: low for blurry frames."""
    inner = [r * width + c for r in range(1, height - 1) for c in range(1, width - 1)]
    at = f"array({', '.join(map(str, inner))})"
    p = lambda o: f"cast({col}[i + ({o})] AS double)"
    lap = f"transform({at}, i -> {p(-width)} + {p(width)} + {p(-1)} + {p(1)} - 4D * {p(0)})"
    n = float(len(inner))
    mean = f"aggregate(l, 0D, (s, x) -> s + x) / {n}D"
    return F.expr(f"transform(array({lap}), l -> transform(array({mean}), m -> aggregate(l, 0D, (s, x) -> s + (x - m) * (x - m)) / {n}D)[0])[0]")


def trim_bounds(col: str, height: int, width: int, tolerance: float = 0.0) -> Column:
    """r0, r1, c0, c1 of what constant rows and columns at the edges leave; null for a constant frame."""
    row = f"filter(sequence(0, {height - 1}), r -> array_max(slice({col}, r * {width} + 1, {width})) - array_min(slice({col}, r * {width} + 1, {width})) > {tolerance})"
    line = f"transform(sequence(0, {height - 1}), r -> {col}[r * {width} + c])"
    column = f"filter(sequence(0, {width - 1}), c -> array_max({line}) - array_min({line}) > {tolerance})"
    return F.expr(f"struct(array_min({row}) AS r0, array_max({row}) AS r1, array_min({column}) AS c0, array_max({column}) AS c1)")


def crop_nearest(col: str, width: int, top: int, left: int, height: int, breadth: int) -> Column:
    """A rectangle of the frame, as an array of doubles."""
    at = [r * width + c for r in range(top, top + height) for c in range(left, left + breadth)]
    return F.expr(f"transform(array({', '.join(map(str, at))}), i -> cast({col}[i] AS double))")


def sample_bilinear(col: str, height: int, width: int, out_height: int, out_width: int, a: str, b: str, c: str, d: str, e: str, f: str) -> Column:
    """A thumbnail of ``out_height`` x ``out_width``: pixel (row i, column j) is the frame at x = a j + b i + c, y = d j + e i + f.

    Between four pixels by bilinear weights; beyond the frame by its nearest edge. The six are column expressions.
    """
    clamp = lambda v, n: f"least(greatest({v}, 0D), {n - 1}D)"
    at = f"transform(sequence(0, {out_height * out_width - 1}), k -> named_struct('x', {clamp(f'({a}) * (k % {out_width}) + ({b}) * (k DIV {out_width}) + ({c})', width)}, 'y', {clamp(f'({d}) * (k % {out_width}) + ({e}) * (k DIV {out_width}) + ({f})', height)}))"
    px = lambda r, q: f"cast({col}[cast({r} * {width} + {q} AS int)] AS double)"
    r0, q0 = "floor(p.y)", "floor(p.x)"
    r1, q1 = f"least({r0} + 1, {height - 1})", f"least({q0} + 1, {width - 1})"
    wy, wx = f"(p.y - {r0})", f"(p.x - {q0})"
    mixed = f"(1D - {wy}) * ((1D - {wx}) * {px(r0, q0)} + {wx} * {px(r0, q1)}) + {wy} * ((1D - {wx}) * {px(r1, q0)} + {wx} * {px(r1, q1)})"
    return F.expr(f"transform({at}, p -> {mixed})")
