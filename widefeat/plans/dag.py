"""The graph of columns: features lead from input columns to output columns."""

from __future__ import annotations

from collections import defaultdict
from collections.abc import Iterable, Sequence
from functools import cached_property

from pyspark.sql import DataFrame, SparkSession

from ..model import FeatureSpec, PlanningError


class FeatureGraph:
    """Adjacency by column; a column without a producer comes from ingestion."""

    def __init__(self, producers: dict[str, FeatureSpec]):
        self.producers = producers
        self._ancestors: dict[str, frozenset[str]] = {}

    @classmethod
    def from_specs(cls, specs: Iterable[FeatureSpec]) -> FeatureGraph:
        return cls({o: s for s in specs for o in s.output_names})

    def parents(self, column: str) -> tuple[str, ...]:
        return self.producers[column].inputs if column in self.producers else ()

    @cached_property
    def children(self) -> dict[str, set[str]]:
        out: dict[str, set[str]] = defaultdict(set)
        for column in self.producers:
            for p in self.parents(column):
                out[p].add(column)
        return out

    def _reach(self, start: str, step) -> frozenset[str]:
        seen: set[str] = set()
        todo = list(step(start))
        while todo:
            c = todo.pop()
            if c not in seen:
                seen.add(c)
                todo += step(c)
        return frozenset(seen)

    def ancestors(self, column: str) -> frozenset[str]:
        if column not in self._ancestors:
            self._ancestors[column] = self._reach(column, self.parents)
        return self._ancestors[column]

    def descendants(self, column: str) -> frozenset[str]:
        return self._reach(column, lambda c: self.children.get(c, ()))

    def check_acyclic(self) -> None:
        for c in self.producers:
            if c in self.ancestors(c):
                raise PlanningError(f"{c} depends on itself")

    def levels(self, columns: Iterable[str]) -> list[list[str]]:
        """Columns by the longest chain of the given columns above them."""
        wanted, level = set(columns), {}

        def of(c: str) -> int:
            if c not in level:
                above = [of(p) for p in self.ancestors(c) if p in wanted and p != c]
                level[c] = 1 + max(above, default=-1)
            return level[c]

        out: dict[int, list[str]] = defaultdict(list)
        for c in sorted(wanted):
            out[of(c)].append(c)
        return [out[k] for k in sorted(out)]

    def topo(self, columns: Sequence[str]) -> list[str]:
        return [c for level in self.levels(columns) for c in level]

    def edges(self) -> list[tuple[str, str, str]]:
        return sorted((c, p, s.name) for c, s in self.producers.items() for p in s.inputs)

    def edges_df(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame(self.edges(), "child string, parent string, feature_id string")
