"""Text queries over stored sketches, and SQL functions for ranks."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from ..operators import estimate
from ..sources import store
from . import predicate as P


class SketchStore:
    """Sketches at a path, made with one k, family and seed.

    store.weight("in(A) and not in(C) and length >= 5"); store.similar("A", "B"); store.batch({1: "...", 2: "..."})."""

    def __init__(self, spark: SparkSession, path: str, *, k: int, family: str = "exponential", seed: int = 0):
        self.spark, self.path, self.k, self.family, self.seed = spark, path, k, family, seed

    def sketches(self) -> DataFrame:
        return store.read_sketches(self.spark, self.path, k=self.k, family=self.family, seed=self.seed)

    def weight(self, text: str, combo: str = "auto") -> DataFrame:
        return estimate.weight(self.sketches(), P.parse(text), combo=combo, family=self.family, k=self.k)

    def batch(self, queries: dict[int, str], combo: str = "auto") -> DataFrame:
        return estimate.weight_batch(self.sketches(), queries, combo=combo, family=self.family, k=self.k)

    def similar(self, a: str, b: str) -> DataFrame:
        pairs = self.spark.createDataFrame([(0, a, b)], "query_id long, a string, b string")
        return estimate.pair(self.sketches(), pairs, self.family)


def register(spark: SparkSession) -> None:
    """SQL functions rank_exp(u, w), rank_pri(u, w), inc_exp(w, t), inc_pri(w, t); Spark inlines them into plans."""
    for name, args, body in (
        ("rank_exp", "u double, w double", "-ln(u) / w"),
        ("rank_pri", "u double, w double", "u / w"),
        ("inc_exp", "w double, t double", "-expm1(-w * t)"),
        ("inc_pri", "w double, t double", "least(1.0D, w * t)"),
    ):
        spark.sql(f"create or replace temporary function {name}({args}) returns double return {body}")


def register_udtf(spark: SparkSession) -> None:
    """sketch_relevant(text): a row for each set that a predicate depends on, and the combination that answers it."""
    from pyspark.sql.functions import udtf

    @udtf(returnType="set_id string, combination string")
    class Relevant:
        def eval(self, text: str):
            p = P.parse(text)
            for s in sorted(P.relevant_sets(p)):
                yield s, P.best_combination(p)

    spark.udtf.register("sketch_relevant", Relevant)
