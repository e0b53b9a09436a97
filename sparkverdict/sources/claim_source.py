"""A Python data source for claim sets: `spark.read.format("claim_set").option("set", "benchmark").load()`.

One input partition per claim style, so a large set of claims is read in parallel; options name the set and, if wanted, the relation."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

SCHEMA = "claim_id string, relation string, style string, form string, text string, expected boolean"


class ClaimSet(DataSource):
    @classmethod
    def name(cls) -> str:
        return "claim_set"

    def schema(self) -> str:
        return SCHEMA

    def reader(self, schema) -> DataSourceReader:
        return _Reader(dict(self.options))


class _Style(InputPartition):
    def __init__(self, style: str) -> None:
        super().__init__(style)


class _Reader(DataSourceReader):
    def __init__(self, options: dict[str, str]) -> None:
        self.options = options

    def partitions(self) -> list[InputPartition]:
        return [_Style(s) for s in ("summarize", "compare", "rank")]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        from sparkverdict import workloads

        sets = {"benchmark": workloads.benchmark, "scale": workloads.scale_up, "kinds": workloads.kinds}
        for c in sets[self.options.get("set", "benchmark")]().values():
            if c.style == partition.value and self.options.get("relation", c.relation) == c.relation:
                yield c.claim_id, c.relation, c.style, type(c.form).__name__, c.text, c.expected
