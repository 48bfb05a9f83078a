"""Sources and sinks: given schemas, no inference; a replay source for engine logs."""

from __future__ import annotations

import numpy as np
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

FORMATS = ("parquet", "json", "csv", "orc", "text", "binaryFile")


def read(spark: SparkSession, kind: str, path: str, schema=None, **options) -> DataFrame:
    if kind not in FORMATS:
        raise ValueError(kind)
    r = spark.read.format(kind).options(**options)
    return (r.schema(schema) if schema is not None and kind not in ("text", "binaryFile") else r).load(path)


def write(df: DataFrame, kind: str, path: str, by: list[str] | None = None, **options) -> None:
    w = df.write.mode("overwrite").format(kind).options(**options)
    (w.partitionBy(*by) if by else w).save(path)


def round_trip(df: DataFrame, kind: str, path: str, **options) -> DataFrame:
    write(df, kind, path, **options)
    return read(df.sparkSession, kind, path, df.schema, **options)


def write_log(replies: DataFrame, path: str) -> None:
    """Logs (rollout_id, turn, token_ids) as a serving engine does: a line a reply, its key and then its tokens."""
    line = F.concat_ws(" ", F.col("rollout_id").cast("string"), F.col("turn").cast("string"), F.col("token_ids").cast("array<string>"))
    replies.select(line.alias("value")).write.text(path)


class EngineLog(DataSource):
    """Replays a serving engine's log of ``write_log`` under ``path`` as (rollout_id, turn, pos, token_id): a task a file. The folder is one that executors share."""

    @classmethod
    def name(cls) -> str:
        return "engine_log"

    def schema(self) -> str:
        return "rollout_id long, turn long, pos int, token_id long"

    def reader(self, schema):
        return EngineLogReader(self.options["path"])


class EngineLogReader(DataSourceReader):
    def __init__(self, path: str, batch: int = 1 << 16):
        self.path, self.batch = path, batch

    def partitions(self):
        from pyarrow import fs

        store, top = fs.FileSystem.from_uri(self.path)
        files = [f.path for f in store.get_file_info(fs.FileSelector(top, recursive=True)) if f.is_file and not f.base_name.startswith(("_", "."))]
        return [InputPartition(f) for f in sorted(files)] or [InputPartition(None)]

    def read(self, partition):
        import io

        from pyarrow import fs

        if partition.value is None:
            return
        rows, n = [], 0
        with fs.FileSystem.from_uri(self.path)[0].open_input_stream(partition.value) as f:
            for line in io.TextIOWrapper(f):
                rows.append(np.array(line.split(), dtype="int64"))
                n += len(rows[-1])
                if n >= self.batch:
                    yield self._batch(rows)
                    rows, n = [], 0
        if rows:
            yield self._batch(rows)

    def _batch(self, rows):
        import pyarrow as pa

        size = np.array([len(r) - 2 for r in rows])
        pos = np.arange(size.sum()) - np.repeat(np.cumsum(size) - size, size)
        key = lambda i: np.repeat(np.array([r[i] for r in rows]), size)
        return pa.RecordBatch.from_arrays([pa.array(key(0)), pa.array(key(1)), pa.array(pos.astype("int32")), pa.array(np.concatenate([r[2:] for r in rows]))], names=["rollout_id", "turn", "pos", "token_id"])
