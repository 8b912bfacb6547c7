"""The derived corpus as a Python data source, split by ranges of questions."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, InputPartition

from densesql.operators import corpus


class _Range(InputPartition):
    def __init__(self, first: int, last: int):
        self.first, self.last = first, last


class _Reader(DataSourceReader):
    def __init__(self, options: dict):
        self.group = int(options.get("group", 32))
        self.parts = int(options.get("partitions", 4))
        self.tier = options.get("tier", "s")
        self.temperature = float(options.get("temperature", 1.0))
        self.only: int | None = None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802 - the interface's name
        """A filter on one question is taken over; the rest goes back to Spark."""
        for f in filters:
            if isinstance(f, EqualTo) and f.attribute == ("question_id",):
                self.only = int(f.value)
            else:
                yield f

    def partitions(self) -> list[InputPartition]:
        if self.only is not None:
            return [_Range(self.only, self.only + 1)] if 0 <= self.only < len(corpus.QUESTIONS) else [_Range(0, 0)]
        n = len(corpus.QUESTIONS)
        cuts = [k * n // self.parts for k in range(self.parts + 1)]
        return [_Range(a, b) for a, b in zip(cuts, cuts[1:], strict=False)]

    def read(self, partition: _Range) -> Iterator[tuple]:
        variety, styles = 1 + round(self.temperature * 31), list(corpus.TEACHERS)
        for q in range(partition.first, partition.last):
            for r in range(self.group):
                at = r % variety
                style = styles[int(corpus.draw(q, at, self.tier, 42, "teacher") * len(styles))]
                names, text, logp = corpus.complete(q, at, self.tier, style, "roll42", corpus.TIERS[self.tier])
                yield q, r, corpus.QUESTIONS[q][0], corpus.QUESTIONS[q][1], self.tier, self.temperature, style, names, text, logp


class RolloutSource(DataSource):
    """``spark.read.format('derived_rollouts')`` with options group, tier, temperature and partitions."""

    @classmethod
    def name(cls) -> str:
        return "derived_rollouts"

    def schema(self) -> str:
        return corpus.ROLLOUT

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")  # a runtime setting, off by default
    spark.dataSource.register(RolloutSource)
