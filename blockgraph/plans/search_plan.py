"""Scan, filter, route, search, merge: planned before any of it runs."""

from __future__ import annotations

from dataclasses import dataclass

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..operators import exact, index


@dataclass
class SearchPlan:
    """A vector query over an index and, for filters, its base table.

    ``filter`` with few survivors is answered exactly on these (pre-filter);
    else the index is searched, and rows outside the filter lead the way but are
    no answers; each segment goes on until it has k rows that are. The choice is
    by the counted share of survivors."""

    base: DataFrame | None = None
    index: DataFrame | None = None
    n_segments: int = 1
    centroids: np.ndarray | None = None
    n_probe: int | None = None
    filter: Column | None = None
    prefilter_share: float = 0.1

    def steps(self, ask: index.Ask) -> list[str]:
        out = ["scan"]
        if self.filter is not None:
            out.append("pre-filter, exact" if self._few() else "search, filter on the way")
        else:
            out.append("search" if self.index is not None else "exact")
        if self.index is not None and out[-1] != "pre-filter, exact":
            out.insert(1, f"route to {self.n_probe} of {self.n_segments} segments" if self.n_probe else f"all {self.n_segments} segments")
        return [*out, "merge"]

    def _few(self) -> bool:
        if self.index is None:
            return True
        n = self.base.agg(F.count(F.lit(1)), F.sum(F.coalesce(self.filter, F.lit(False)).cast("long"))).first()
        return (n[1] or 0) <= self.prefilter_share * max(n[0], 1)

    def routed(self, queries: DataFrame) -> DataFrame:
        if self.n_probe and self.centroids is not None:
            return index.route(queries, self.centroids, self.n_probe)
        return index.everywhere(queries, self.n_segments)

    def run(self, queries: DataFrame, ask: index.Ask, metric: str = "l2") -> DataFrame:
        k = None if ask.r is not None else ask.k
        if self.index is None or self.filter is not None and self._few():
            base = self.base if self.filter is None else self.base.where(self.filter)
            return exact.knn(base, queries, k, metric) if k else exact.radius(base, queries, ask.r, metric)
        if self.filter is None:
            return index.merge(index.run_queries(self.index, self.routed(queries), ask), k)
        keep = self.base.where(self.filter).select("vec_id")
        return index.merge(index.run_queries(self.index, self.routed(queries), ask, visible=keep), k)
