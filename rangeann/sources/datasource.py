"""The saved index as a data source: ``spark.read.format("rangeann")``.

Options: ``path`` (a folder that ``Index.save`` wrote; a local path or a URI that pyarrow's file systems know, readable by driver and
executors), ``query`` (numbers between commas), ``lq``, ``rq``, ``mask``, ``k``, ``ef``.  A partition is a file of shards that the interval
can concern, by the shards' bounds; each gives its best k, so the reader's rows are merged by ``orderBy("dist", "id").limit(k)``.
"""

from __future__ import annotations

import json

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

BOUNDS = ["l_min", "l_max", "r_min", "r_max"]


class ShardFile(InputPartition):
    def __init__(self, path: str, rows: list[int]):
        self.path, self.rows = path, rows


class RangeIndexReader(DataSourceReader):
    def __init__(self, options: dict):
        self.options = options

    def opened(self):
        """The file system and the folder in it."""
        from pyarrow import fs

        path = self.options["path"]
        return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)

    def files(self, part: str, ending: str) -> list[str]:
        from pyarrow import fs

        system, folder = self.opened()
        return sorted(f.path for f in system.get_file_info(fs.FileSelector(f"{folder}/{part}")) if f.path.endswith(ending))

    def meta(self) -> dict:
        system, _ = self.opened()
        for f in self.files("meta", ".txt"):
            with system.open_input_stream(f) as stream:
                data = stream.read()
            if data.strip():
                return json.loads(data)
        raise ValueError("the folder has no index")

    def asked(self, meta: dict) -> tuple:
        from rangeann.functions.predicates import plan

        o = self.options
        number = float if meta["kind"] == "double" else int
        return plan(int(o.get("mask", 15))), number(o["lq"]), number(o["rq"])

    def partitions(self):
        import pyarrow.parquet as pq

        from rangeann.operators.index import concerns

        system, _ = self.opened()
        boxes, lq, rq = self.asked(self.meta())
        out = []
        for f in self.files("shards", ".parquet"):
            bounds = pq.read_table(f, columns=BOUNDS, filesystem=system).to_pylist()
            rows = [i for i, b in enumerate(bounds) if any(concerns(box, lq, rq, b) for box in boxes)]
            if rows:
                out.append(ShardFile(f, rows))
        return out

    def read(self, partition):
        import numpy as np
        import pyarrow.parquet as pq

        from rangeann.operators.index import answers, opened

        o, meta = self.options, self.meta()
        boxes, lq, rq = self.asked(meta)
        system, _ = self.opened()
        q = np.array([float(x) for x in o["query"].split(",")])
        for row in pq.read_table(partition.path, filesystem=system).take(partition.rows).to_pylist():
            shard, trees = opened(row, meta["m"], meta["small"], np.float64 if meta["kind"] == "double" else np.int64, boxes)
            for _, i, dist, *_ in answers(row, shard, trees, boxes, [(0, q, lq, rq)], int(o.get("k", 10)), int(o.get("ef", 100))):
                if i is not None:
                    yield (i, dist)


class RangeIndexSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "rangeann"

    def schema(self) -> str:
        return "id long, dist double"

    def reader(self, schema) -> DataSourceReader:
        return RangeIndexReader(dict(self.options))
