"""Filter ordering, chain execution and their cost.

The optimizer of Spark keeps the order of expensive conjuncts, so the order is chosen here, before a plan is built.
Costs come from the histogram of truth masks: one scan of the items prices every query in every order.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field
from itertools import permutations

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F


@dataclass(frozen=True)
class CostModel:
    """Seconds of one model call, of a learned radius and of one batch of compressed answers; bytes of a full state and of a vector."""

    call_s: float = 1.0
    learned_s: float = 0.017
    batch_s: float = 0.9
    state_bytes: int = 300_000_000
    vector_bytes: int = 4608

    def estimation(self) -> Column:
        """Seconds of one estimate by the columns method and m; a blended radius takes a probe and a prediction."""
        method = F.col("method")
        cost = F.when(method == "profile", F.col("m") * self.call_s).when(method.isin("probed", "compressed"), F.lit(self.batch_s))
        return cost.when(method == "learned", F.lit(self.learned_s)).when(method.isin("blended", "blended_compressed"), F.lit(self.batch_s + self.learned_s)).otherwise(F.lit(0.0))


def random_queries(spark: SparkSession, concepts: DataFrame, per_size: int = 100, sizes: tuple[int, ...] = (2, 3, 4)) -> DataFrame:
    """query_id, n_filters, concept_id, pos: distinct filters per query, drawn by hash."""
    count = per_size * len(sizes)
    of = F.array(*map(F.lit, sizes))
    q = spark.range(count).select(F.col("id").alias("query_id"), F.element_at(of, (F.col("id") / per_size).cast("int") + 1).alias("n_filters"))
    order = Window.partitionBy("query_id").orderBy(F.md5(F.concat_ws(":", "query_id", "concept_id")), "concept_id")
    drawn = q.crossJoin(F.broadcast(concepts.select("concept_id", "pos"))).withColumn("r", F.row_number().over(order))
    return drawn.filter("r <= n_filters").withColumnRenamed("r", "written")


def order_filters(queries: DataFrame, estimates: DataFrame, keys: list[str], rank: str = "estimate") -> DataFrame:
    """Adds step: the place of each filter by ascending estimate (ties by concept); keys tell the estimators apart."""
    order = Window.partitionBy(*keys, "query_id").orderBy(rank, "concept_id")
    return queries.join(F.broadcast(estimates), "concept_id").withColumn("step", F.row_number().over(order))


def chain_steps(ordered: DataFrame, masks: DataFrame, keys: list[str]) -> DataFrame:
    """keys, query_id, step, calls: how many items reach each filter. The histogram has a row per combination that occurs."""
    before = Window.partitionBy(*keys, "query_id").orderBy("step").rowsBetween(Window.unboundedPreceding, -1)
    prefix = ordered.withColumn("need", F.coalesce(F.sum(F.expr("shiftleft(1L, pos)")).over(before), F.lit(0)))
    reached = prefix.select(*keys, "query_id", "n_filters", "step", "concept_id", "need")
    needs = reached.select("need").distinct().join(F.broadcast(masks), F.col("mask").bitwiseAND(F.col("need")) == F.col("need"), "left")
    calls = needs.groupBy("need").agg(F.coalesce(F.sum("n"), F.lit(0)).alias("calls"))
    return reached.join(calls, "need").drop("need")


def chain_calls(ordered: DataFrame, masks: DataFrame, keys: list[str]) -> DataFrame:
    return chain_steps(ordered, masks, keys).groupBy(*keys, "query_id", "n_filters").agg(F.sum("calls").alias("calls"))


def best_orders(queries: DataFrame, masks: DataFrame) -> DataFrame:
    """query_id, n_filters, calls of the cheapest of all orders (at most 4! per query)."""
    spark = queries.sparkSession
    places = spark.createDataFrame([(n, k, w + 1, s + 1) for n in (2, 3, 4) for k, p in enumerate(permutations(range(n))) for w, s in enumerate(p)], "n_filters int, perm int, written int, step int")
    tried = queries.join(F.broadcast(places), ["n_filters", "written"])
    return chain_calls(tried, masks, ["perm"]).groupBy("query_id", "n_filters").agg(F.min("calls").alias("calls"))


@dataclass
class SemanticQuery:
    """A conjunction of text filters over items; `optimize` orders them by estimates, `execute` runs them with short-circuiting."""

    items: DataFrame
    filters: list[tuple[str, list[str], list[str]]] = field(default_factory=list)

    def where(self, concept: tuple[str, list[str], list[str]]) -> SemanticQuery:
        return SemanticQuery(self.items, [*self.filters, concept])

    def optimize(self, estimates: DataFrame) -> SemanticQuery:
        names = [c[0] for c in self.filters]
        known = {r["concept_id"]: r["estimate"] for r in estimates.filter(F.col("concept_id").isin(names)).select("concept_id", "estimate").collect()}
        return SemanticQuery(self.items, sorted(self.filters, key=lambda c: (known.get(c[0], 1.0), c[0])))

    def execute(self, model: Callable[[tuple, list[dict]], list[bool]] | None = None) -> DataFrame:
        """Survivors with `calls`, the model calls spent on each. All filters run in one operator: as separate Python filters Spark would evaluate every one of them on every row."""
        chain = self.filters
        model = model or (lambda concept, rows: [set(concept[1]) <= set(r["toks"]) and (not concept[2] or bool(set(concept[2]) & set(r["toks"]))) for r in rows])

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                rows, calls = batch.to_pylist(), [0] * batch.num_rows
                alive = list(range(batch.num_rows))
                for concept in chain:
                    said = model(concept, [rows[i] for i in alive])
                    for i in alive:
                        calls[i] += 1
                    alive = [i for i, yes in zip(alive, said, strict=True) if yes]
                ok = set(alive)
                yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(calls, pa.int32()), pa.array([i in ok for i in range(batch.num_rows)], pa.bool_())], ["item_id", "calls", "passed"])

        return self.items.select("item_id", "toks").mapInArrow(run, "item_id long, calls int, passed boolean")
