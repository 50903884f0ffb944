"""``spark.read.format("lookalike_graph")``: edge lists of conversation paths and the like, read by Python tasks.

Options: ``sf_dir``, ``parts``. One partition per residue of the conversation id, each read by
Arrow with a pushed filter; for stores that Arrow can open.
"""

from __future__ import annotations

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class GraphSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "lookalike_graph"

    def schema(self) -> str:
        return "src BIGINT, dst BIGINT"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.path = f"{options['sf_dir']}/conversations.parquet"
        self.parts = int(options.get("parts", 4))

    def partitions(self):
        return [InputPartition(i) for i in range(self.parts)]

    def read(self, partition):
        import pyarrow.dataset as ds

        t = ds.dataset(self.path).to_table(columns=["conv_id", "turn"]).to_pydict()
        turns = sorted({(c, n) for c, n in zip(t["conv_id"], t["turn"], strict=True) if c % self.parts == partition.value})
        have = set(turns)
        for c, n in turns:
            if (c, n + 1) in have:
                yield (c * 100000 + n, c * 100000 + n + 1)
