"""Deterministic pseudo-random order and samples, equal in every SQL engine."""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column
from pyspark.sql import functions as F

MULT, MOD = 2654435761, 4294967296


def mixed(col: Column) -> Column:
    return F.pmod(col.cast("long") * F.lit(MULT), F.lit(MOD))


def in_sample(col: Column, ratio: float) -> Column:
    return mixed(col) < F.lit(int(ratio * MOD))


def mixed_np(ids: np.ndarray) -> np.ndarray:
    return (np.asarray(ids, np.int64) * MULT) % MOD
