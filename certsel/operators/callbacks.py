"""What users plug in: oracles as Python callbacks, asked once for a key over all runs, and table functions."""

from __future__ import annotations

from collections.abc import Callable

import pandas as pd
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from certsel.operators import runner, sampling
from certsel.sources.staging import fresh_path
from certsel.sources.tables import read_ledger, save_ledger
from certsel.spec import SelectionSpec


def as_oracle(ask: Callable[..., pd.Series], *columns: str) -> Callable[[DataFrame], DataFrame]:
    """An oracle from a function over pandas columns that gives 0 or 1.  Spark may neither move nor repeat its calls."""

    def asked(*args: pd.Series) -> pd.Series:
        return ask(*args).fillna(0).astype("int32")

    udf = F.pandas_udf(asked, "int").asNondeterministic()
    return lambda df: df.withColumn("y", udf(*columns))


class Ledger:
    """Labels bought so far, in a table that later runs read before they ask."""

    def __init__(self, spark: SparkSession, path: str, key: str = "key"):
        self.spark, self.path, self.key, self.calls = spark, path, key, 0

    def metered(self, oracle: Callable[[DataFrame], DataFrame]) -> Callable[[DataFrame], DataFrame]:
        """The oracle for new keys alone: their labels are appended first, so a failure later costs no label twice."""

        def label(df: DataFrame) -> DataFrame:
            known = read_ledger(self.spark, self.path, df.schema[self.key].dataType)
            new = df.join(known.select(self.key), self.key, "left_anti")
            before = known.count()
            save_ledger(oracle(new), self.path)
            bought = read_ledger(self.spark, self.path, df.schema[self.key].dataType)
            self.calls += bought.count() - before
            return df.join(bought, self.key)

        return label


def replay(spark: SparkSession, sf_dir: str, spec: SelectionSpec) -> DataFrame:
    """The rare events by a callback oracle with a ledger, twice: the second run asks nothing and gives the same rows."""
    from certsel.sources.workloads import ALL

    oracle = as_oracle(lambda kind, value: ((kind == "purchase") & (value > 200)).astype("int32"), "event_type", "value")
    ledger = Ledger(spark, fresh_path(spark, "ledger"))
    base = ALL["rare"].scored(spark, sf_dir)
    first = runner.run(base, ledger.metered(oracle), spec).rows.select("key", "score_u")
    calls, ledger.calls = ledger.calls, 0
    again = runner.run(base, ledger.metered(oracle), spec).rows.select("key", F.lit(True).alias("again"))
    both = first.join(again, "key", "left")
    return both.select("key", "score_u", F.coalesce("again", F.lit(False)).alias("same_again"), F.lit(calls).cast("long").alias("calls"), F.lit(ledger.calls).cast("long").alias("calls_again"))


def grid(spark: SparkSession, sf_dir: str, budget: int, step: int) -> DataFrame:
    """(candidate, draws, score_u): the grid that precision goals test, from a Python table function, with each candidate's cut in a sample of the rare events."""
    from certsel.sources.workloads import ALL
    from pyspark.sql import Window
    from pyspark.sql.functions import udtf

    @udtf(returnType="candidate int, draws int")
    class Candidates:
        def eval(self, budget: int, step: int):
            for k in range(1, budget // step + 1):
                yield k, k * step

    drawn = sampling.uniform_distinct(ALL["rare"].scored(spark, sf_dir), budget, 1, 0)
    drawn = drawn.select("score_u", F.row_number().over(Window.orderBy(F.desc("score_u"), "key")).alias("draws"))
    return Candidates(F.lit(budget), F.lit(step)).join(drawn, "draws").select("candidate", "draws", "score_u")
