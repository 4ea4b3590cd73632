"""``spark.read.format("vecpath_index")``: a stored graph index as a table of nodes or links."""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, In, InputPartition

from ..operators.graph import Shard

SCHEMAS = {
    "nodes": "shard long, node long, id long, level long, vec array<double>",
    "edges": "shard long, level long, node long, neighbours array<int>",
}


class IndexSource(DataSource):
    """Options: ``path`` of a saved index, ``table`` nodes (default) or edges."""

    @classmethod
    def name(cls) -> str:
        return "vecpath_index"

    def schema(self) -> str:
        return SCHEMAS[self.options.get("table", "nodes")]

    def reader(self, schema) -> IndexReader:
        return IndexReader(self.options)


def register(spark) -> None:
    """Install the source; the session must let Python sources see filters."""
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IndexSource)


class IndexReader(DataSourceReader):
    """One partition for each shard; a filter on the shard prunes partitions."""

    def __init__(self, options):
        self.path, self.table = options["path"], options.get("table", "nodes")
        self.shards: set[int] | None = None

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:
        for f in filters:
            wanted = None
            if isinstance(f, EqualTo) and f.attribute == ("shard",):
                wanted = {f.value}
            elif isinstance(f, In) and f.attribute == ("shard",):
                wanted = set(f.value)
            if wanted is None:
                yield f
            else:
                self.shards = wanted if self.shards is None else self.shards & wanted

    def _files(self):
        import pyarrow.dataset as ds
        from pyarrow import fs

        store, root = fs.FileSystem.from_uri(self.path if "://" in self.path else f"file://{self.path}")
        return ds.dataset(root, filesystem=store, format="parquet", partitioning="hive")

    def partitions(self) -> list[InputPartition]:
        shards = sorted({s.as_py() for s in self._files().to_table(columns=["shard"]).column("shard").unique()})
        return [InputPartition(s) for s in shards if self.shards is None or s in self.shards]

    def read(self, partition: InputPartition) -> Iterator[tuple]:
        import pyarrow.dataset as ds

        rows = self._files().to_table(filter=ds.field("shard") == partition.value).to_pylist()
        for r in rows:
            g = Shard.unpack(*(r[c] for c in ("n", "dim", "ids", "vecs", "levels", "degrees", "edges")))
            for i in range(len(g.ids)):
                if self.table == "nodes":
                    yield (int(r["shard"]), i, int(g.ids[i]), int(g.levels[i]), [float(x) for x in g.vecs[i]])
                else:
                    for level, links in enumerate(g.links[i]):
                        yield (int(r["shard"]), level, i, [int(x) for x in links])
