"""The stored index as a data source: ``spark.read.format('corpusbwt').load(path)``, one partition a shard.

Filters on ``pos`` and ``shard_id`` prune shards before anything is read.
"""

from __future__ import annotations

from collections.abc import Iterable, Iterator

import pyarrow as pa
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThan, GreaterThanOrEqual, InputPartition, LessThan, LessThanOrEqual


class _Shard(InputPartition):
    def __init__(self, files: list[str], shard: int, start: int):
        self.files, self.shard, self.start = files, shard, start


class IndexReader(DataSourceReader):
    def __init__(self, options: dict):
        self.path = options["path"].rstrip("/")
        self.low, self.high, self.only = 0, None, None

    def pushFilters(self, filters: list[Filter]) -> Iterable[Filter]:
        for f in filters:
            if f.attribute == ("pos",) and isinstance(f, GreaterThan | GreaterThanOrEqual | EqualTo):
                self.low = max(self.low, f.value)
            if f.attribute == ("pos",) and isinstance(f, LessThan | LessThanOrEqual | EqualTo):
                self.high = f.value if self.high is None else min(self.high, f.value)
            if f.attribute == ("shard_id",) and isinstance(f, EqualTo):
                self.only = f.value
            yield f  # Spark still applies them to the rows

    def _manifest(self):
        import json

        from pyarrow import fs

        place, root = fs.FileSystem.from_uri(self.path) if "://" in self.path or self.path.startswith("file:") else (fs.LocalFileSystem(), self.path)
        names = [i.path for i in place.get_file_info(fs.FileSelector(f"{root}/manifest")) if i.base_name.startswith("v")]
        with place.open_input_stream(max(names, key=lambda n: int(n.rsplit("/v", 1)[1][:-5]))) as file:
            return place, root, json.loads(file.read())

    def partitions(self) -> list[InputPartition]:
        from pyarrow import fs

        place, root, told = self._manifest()
        self.told, out, at = told, [], 0
        for s in told["shards"]:
            end = at + s["n_sym"]
            if (self.high is None or at <= self.high) and end > self.low and self.only in (None, s["shard_id"]):
                folder = f"{root}/pages/v{s['version']}"
                out.append(_Shard([i.path for i in place.get_file_info(fs.FileSelector(folder)) if i.path.endswith(".parquet")], s["shard_id"], at))
            at = end
        return out

    def read(self, partition: _Shard) -> Iterator[pa.RecordBatch]:
        import numpy as np
        import pyarrow.dataset as ds

        from corpusbwt.functions.alphabet import Alphabet
        from corpusbwt.plans.store import PageCodec

        place, _, told = self._manifest()
        alphabet = Alphabet(tuple(told["points"]))
        codec, points = PageCodec(alphabet.sigma, alphabet.bits, told["spacing"], told["packing"]), np.array((0, *told["points"]), np.int32)
        pages = ds.dataset(partition.files, filesystem=place).to_table(columns=["start_in_shard", "n_sym", "payload"], filter=ds.field("shard_id") == partition.shard)
        for start, n, payload in zip(*(c.to_pylist() for c in pages.columns), strict=True):
            pos = np.arange(n) + partition.start + start
            yield pa.RecordBatch.from_arrays([pa.array(np.full(n, partition.shard, np.int32)), pa.array(pos), pa.array(points[codec.symbols(payload, n)])], ["shard_id", "pos", "sym"])


class IndexDataSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "corpusbwt"

    def schema(self) -> str:
        return "shard_id int, pos long, sym int"

    def reader(self, schema) -> IndexReader:
        return IndexReader(self.options)


def register(spark: SparkSession) -> None:
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(IndexDataSource)
