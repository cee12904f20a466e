"""Per-scene kernels over one shuffle: scenes are dealt by key, sorted, and
streamed through Arrow batches, so a task holds one scene at a time and small
scenes cost no call of their own."""

from __future__ import annotations

from collections.abc import Callable

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import types as T

from ..session import prepare

_ARROW = {"bigint": pa.int64(), "int": pa.int32(), "double": pa.float64(), "string": pa.string(), "boolean": pa.bool_()}


def arrow_schema(ddl: str) -> pa.Schema:
    return pa.schema([(n, _ARROW[k]) for n, k in (c.strip().split(" ") for c in ddl.split(","))])


def scenes_of(batches, key: str):
    """(key, table) of each run of equal keys in sorted batches."""
    held: list[pa.RecordBatch] = []
    now = None
    for b in batches:
        if not b.num_rows:
            continue
        k = b.column(b.schema.get_field_index(key)).to_numpy(zero_copy_only=False)
        cuts = np.concatenate([[0], np.flatnonzero(k[1:] != k[:-1]) + 1, [len(k)]])
        for a, e in zip(cuts[:-1], cuts[1:]):
            if held and k[a] != now:
                yield now, pa.Table.from_batches(held)
                held = []
            now = k[a]
            held.append(b.slice(a, e - a))
    if held:
        yield now, pa.Table.from_batches(held)


def per_scene(df: DataFrame, kernel: Callable[[int, dict[str, np.ndarray]], dict], ddl: str, key: str = "scene_id", order: tuple[str, ...] = (), flat: tuple[str, ...] = ()) -> DataFrame:
    """kernel(scene, columns) -> columns of ddl, for every scene.  Array columns
    arrive as object arrays, those named in flat as all their values in row order."""
    dealt = df.repartition(key).sortWithinPartitions(key, *order)
    return per_dealt_scene(dealt, kernel, ddl, key, flat)


def per_dealt_scene(df: DataFrame, kernel: Callable[[int, dict[str, np.ndarray]], dict], ddl: str, key: str = "scene_id", flat: tuple[str, ...] = ()) -> DataFrame:
    """per_scene without its shuffle, for rows that lie scene after scene, each whole in a task."""
    prepare(df.sparkSession)
    schema = arrow_schema(ddl)
    lists = {f.name for f in df.schema.fields if isinstance(f.dataType, T.ArrayType)}

    def work(it):
        last = None
        for scene, t in scenes_of(it, key):
            if last is not None and scene <= last:
                raise RuntimeError("scenes do not lie one after the other")
            last = scene
            cols = {}
            for n in t.schema.names:
                c = t.column(n).combine_chunks()
                if n in flat:
                    cols[n] = c.flatten().to_numpy(zero_copy_only=False)
                else:
                    cols[n] = np.fromiter(c.to_pylist(), object, len(c)) if n in lists else c.to_numpy(zero_copy_only=False)
            out = kernel(int(scene), cols)
            n = len(next(v for k, v in out.items() if k != key)) if out else 0
            if n:
                out.setdefault(key, np.full(n, scene))
                yield pa.RecordBatch.from_arrays([pa.array(out[f.name], f.type, from_pandas=True) for f in schema], schema=schema)

    return df.mapInArrow(work, ddl)
