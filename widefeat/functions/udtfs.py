"""Table functions for SQL: the lineage of a column."""

from __future__ import annotations

from pyspark.sql import SparkSession
from pyspark.sql.functions import udtf


def register_lineage(session: SparkSession, edges: list[tuple[str, str, str]], name: str = "lineage_of") -> None:
    """lineage_of(column): its ancestors with the feature and distance; the graph goes along with the function."""
    parents: dict[str, list[tuple[str, str]]] = {}
    for child, parent, feature in edges:
        parents.setdefault(child, []).append((parent, feature))

    class Lineage:
        def eval(self, column: str):
            seen, todo = {column}, [(column, 0)]
            while todo:
                c, d = todo.pop(0)
                for p, f in parents.get(c, []):
                    if p not in seen:
                        seen.add(p)
                        todo.append((p, d + 1))
                        yield p, f, d + 1

    session.udtf.register(name, udtf(Lineage, returnType="ancestor string, feature string, distance int"))
