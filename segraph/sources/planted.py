"""A data source of planted scenes: without input files, for scale tests, or a scene for
every key of a Parquet table (options table and key).

spark.dataSource.register(PlantedScenes)
spark.read.format("planted_scenes").option("scenes", 1000).option("side", 64).load()
"""

from __future__ import annotations

from collections.abc import Iterator

from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


class _Part(InputPartition):
    def __init__(self, first: int, last: int, file: str = "", group: int = 0):
        self.first, self.last, self.file, self.group = first, last, file, group


def _parquet(path: str):
    """(file system, path in it) of a local path or a URI that Arrow knows."""
    from pyarrow import fs

    return fs.FileSystem.from_uri(path) if "://" in path or path.startswith("file:") else (fs.LocalFileSystem(), path)


class _Reader(DataSourceReader):
    def __init__(self, options):
        self.scenes, self.side = int(options.get("scenes", 10)), int(options.get("side", 32))
        self.parts = int(options.get("partitions", 8))
        self.eps = float(options.get("eps", 0.45))
        self.table, self.key = options.get("table", ""), options.get("key", "")

    def partitions(self):
        if self.table:  # a row group a task
            import pyarrow.dataset as ds
            import pyarrow.parquet as pq

            at, path = _parquet(self.table)
            files = ds.dataset(path, filesystem=at, format="parquet").files
            return [_Part(0, 0, f, g) for f in files for g in range(pq.ParquetFile(f, filesystem=at).num_row_groups)]
        cuts = [self.scenes * i // self.parts for i in range(self.parts + 1)]
        return [_Part(a, b) for a, b in zip(cuts, cuts[1:]) if b > a]

    def _scenes(self, part):
        if not part.file:
            return range(part.first, part.last)
        import pyarrow.parquet as pq

        got = pq.ParquetFile(part.file, filesystem=_parquet(self.table)[0]).read_row_group(part.group, [self.key])
        return got.column(0).drop_null().to_pylist()

    def read(self, partition) -> Iterator[tuple]:
        import numpy as np

        n = self.side
        for s in self._scenes(partition):
            rng = np.random.Generator(np.random.PCG64(abs(s)))
            inst = np.zeros((n, n), int)
            for k in range(1, 6):
                y, x = rng.integers(0, n, 2)
                h, w = rng.integers(n // 8 + 1, n // 2 + 1, 2)
                inst[y : y + h, x : x + w] = k
            pix = np.arange(n * n).reshape(n, n)
            for a, b in ((np.s_[:, :-1], np.s_[:, 1:]), (np.s_[:-1], np.s_[1:])):
                same = inst[a] == inst[b]
                aff = np.where(same, 1 - self.eps * rng.random(same.shape), self.eps * rng.random(same.shape))
                keep = (inst[a] > 0) & (inst[b] > 0)
                for u, v, f in zip(pix[a][keep].tolist(), pix[b][keep].tolist(), aff[keep].tolist()):
                    yield s, u, v, f


class PlantedScenes(DataSource):
    @classmethod
    def name(cls) -> str:
        return "planted_scenes"

    def schema(self) -> str:
        return "scene_id bigint, u bigint, v bigint, aff double"

    def reader(self, schema) -> DataSourceReader:
        return _Reader(self.options)
