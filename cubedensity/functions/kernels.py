"""Integer kernels: as column expressions (whole-stage code) and as numpy tables, from the same formulas.

A difference is voxel minus event, in lattice steps. The printed pair is not symmetric: it grows towards smaller
coordinates. ``mirrored`` takes absolute differences, ``epanechnikov`` is the common one of published work, and
``uniform`` counts.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F


def _square(c):
    return c * c


def spatial(kernel: str, dx, dy, hx):
    """Numerator of the spatial factor; works on columns and on arrays."""
    if kernel == "printed":
        return _square(hx - dx) * _square(hx - dy)
    if kernel == "mirrored":
        size = F.abs if isinstance(dx, Column) else np.abs
        return _square(hx - size(dx)) * _square(hx - size(dy))
    if kernel == "epanechnikov":
        return hx * hx - dx * dx - dy * dy
    return F.lit(1).cast("long") if isinstance(dx, Column) else np.ones(np.broadcast(dx, dy).shape, np.int64)


def temporal(kernel: str, dt, ht):
    if kernel == "printed":
        return _square(ht - dt)
    if kernel == "mirrored":
        return _square(ht - (F.abs(dt) if isinstance(dt, Column) else np.abs(dt)))
    if kernel == "epanechnikov":
        return ht * ht - dt * dt
    return F.lit(1).cast("long") if isinstance(dt, Column) else np.ones(np.shape(dt), np.int64)


def in_disk(dx, dy, hx):
    """Open edge in space, under either edge rule."""
    return dx * dx + dy * dy < hx * hx


def in_bar(edge: str, dt, ht):
    size = F.abs(dt) if isinstance(dt, Column) else np.abs(dt)
    return size <= ht if edge == "closed_time" else size < ht
