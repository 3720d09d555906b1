"""SQL surface: table functions over driver-size inputs, and views."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.functions import udtf

from depstrata import theory
from depstrata.plans.features import Path
from depstrata.plans.features import subpaths as _subpaths
from depstrata.plans.tree import SchemaTree


class _Nodes:
    def eval(self, tree: str):
        for node, parent, depth, kind, _, error in SchemaTree.from_json(tree).rows():
            yield node, parent, depth, kind, error


class _Subpaths:
    def eval(self, path: str):
        levels = tuple(x.strip() for x in path.split(">"))
        for i, way in enumerate(_subpaths(Path("", levels, True))):
            yield i, " > ".join(way)


class _Probabilities:
    def eval(self, sizes: str):
        for i, p in enumerate(theory.return_probabilities([int(x) for x in sizes.split(",")])):
            yield i, float(p)


def register(spark: SparkSession) -> None:
    """tree_nodes(json), subpaths('a > b > c'), return_probabilities('1,2,3') for SQL."""
    spark.udtf.register("tree_nodes", udtf(_Nodes, returnType="node string, parent string, depth int, kind string, error double"))
    spark.udtf.register("subpaths", udtf(_Subpaths, returnType="id int, path string"))
    spark.udtf.register("return_probabilities", udtf(_Probabilities, returnType="id int, probability double"))


def views(tables: dict[str, DataFrame]) -> None:
    for name, df in tables.items():
        df.createOrReplaceTempView(name)
