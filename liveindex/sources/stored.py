"""A data source of stored live indexes: spark.read.format("liveindex").load(path) gives the blocks of the newest
snapshot, option `version` those of an older one. One partition a bucket of terms: its files are read a row group at a
time, final blocks are handed on as they come, and of the open blocks the newest of each list is kept to the end.

Register it once a session with `register`."""

from __future__ import annotations

import json
from collections.abc import Iterator

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from liveindex.operators.packer import BLOCKS, _NAMES


def _opened(path: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(path)


class _Bucket(InputPartition):
    def __init__(self, files: list[str], gone: list[int]) -> None:
        super().__init__(None)
        self.files, self.gone = files, gone


class _Reader(DataSourceReader):
    def __init__(self, path: str, version: str | None) -> None:
        self.path, self.version = path, version

    def partitions(self) -> list[_Bucket]:
        from pyarrow import fs

        system, where = _opened(self.path)
        names = sorted(f.path for f in system.get_file_info(fs.FileSelector(where)) if f.base_name.startswith("manifest-"))
        if self.version is not None:
            names = [n for n in names if n.endswith(f"-{int(self.version):012d}")]
        if not names:
            raise FileNotFoundError(f"no index in {self.path}")
        with system.open_input_file(names[-1]) as f:
            now = json.loads(f.read())
        buckets: dict[str, list[str]] = {}
        for batch in now["batches"]:
            for f in system.get_file_info(fs.FileSelector(f"{where}/{batch}", recursive=True, allow_not_found=True)):
                if f.is_file and f.path.endswith(".parquet"):
                    buckets.setdefault(f.path.split("term_bucket=")[1].split("/")[0], []).append(f.path)
        gone = [s["shard"] for s in now["static"]]
        return [_Bucket(files, gone) for _, files in sorted(buckets.items())] or [_Bucket([], gone)]

    def read(self, partition: _Bucket) -> Iterator[pa.RecordBatch]:
        from pyarrow import parquet

        system, _ = _opened(self.path)
        newest: dict[tuple, tuple] = {}
        for name in partition.files:
            file = parquet.ParquetFile(system.open_input_file(name))
            for batch in file.iter_batches(columns=[*_NAMES, "open", "batch_no"]):
                table = pa.Table.from_batches([batch])
                if partition.gone:
                    table = table.filter(pc.invert(pc.is_in(table.column("shard"), pa.array(partition.gone, pa.int64()))))
                done = table.filter(pc.invert(table.column("open"))).select(_NAMES)
                kind = pc.if_else(pc.equal(done.column("block_no"), 1), "head", "full")
                yield from done.set_column(_NAMES.index("kind"), "kind", kind).combine_chunks().to_batches()
                for row in table.filter(table.column("open")).to_pylist():
                    key = (row["shard"], row["term"])
                    if key not in newest or newest[key]["batch_no"] < row["batch_no"]:
                        newest[key] = row
        rows = [{**{c: r[c] for c in _NAMES}, "kind": "head" if r["block_no"] == 1 else "tail"} for r in newest.values()]
        if rows:
            kinds = {"long": pa.int64(), "string": pa.string(), "binary": pa.binary()}
            yield pa.RecordBatch.from_pylist(rows, pa.schema([(c.split()[0], kinds[c.split()[1]]) for c in BLOCKS.split(", ")]))


class LiveIndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "liveindex"

    def schema(self) -> str:
        return BLOCKS

    def reader(self, schema) -> _Reader:
        return _Reader(self.options["path"], self.options.get("version"))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(LiveIndexSource)
