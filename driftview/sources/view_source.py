"""A view as a Spark data source: ``spark.read.format("modelview").load(path of the view)``.

It reads the round that the manifest names, and takes filters on class, eps and
id down to the files.  Plans over the view itself are faster; this is for
readers that know only a path.
"""

from __future__ import annotations

import json
from collections.abc import Iterator
from dataclasses import dataclass

import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds
from pyarrow import fs as pafs
from pyspark.sql import SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, EqualTo, Filter, GreaterThanOrEqual, In, InputPartition, LessThan

from driftview.shipping import ship


@dataclass
class Part(InputPartition):
    file: str
    kind: str
    bucket: int


def _open(path: str) -> tuple[pafs.FileSystem, str]:
    return pafs.FileSystem.from_uri(path) if ":" in path.split("/")[0] else (pafs.LocalFileSystem(), path)


class ViewReader(DataSourceReader):
    def __init__(self, path: str) -> None:
        self.path = path.rstrip("/")
        self.filters: list[tuple[str, str, object]] = []

    def pushFilters(self, filters: list[Filter]) -> Iterator[Filter]:  # noqa: N802
        for f in filters:
            name = f.attribute[0] if len(getattr(f, "attribute", ())) == 1 else None
            kind = {EqualTo: "eq", In: "in", GreaterThanOrEqual: "ge", LessThan: "lt"}.get(type(f))
            if name in ("id", "class", "eps") and kind:
                self.filters.append((name, kind, f.value))
            else:
                yield f

    def _manifest(self) -> dict:
        files, root = _open(self.path)
        with files.open_input_stream(f"{root}/manifest.json") as f:
            return json.loads(f.read())

    def partitions(self) -> list[Part]:
        state = self._manifest()
        if state["policy"] != "eager" or state["arch"] == "memory" or state["band"] == "pairwise" or state["n_deleted"]:
            raise ValueError("only an eager view on disk, without removals since it was clustered, can be read from its files alone")
        files, root = _open(self.path)
        version = f"{root}/v={state['base_version']}"
        classes = {v for n, k, v in self.filters if (n, k) == ("class", "eq")}
        parts = []
        splits = [float("-inf"), *state["bucket_splits"], float("inf")]
        for info in files.get_file_info(pafs.FileSelector(f"{version}/base", recursive=True)):
            if not info.path.endswith(".parquet"):
                continue
            bucket = int(info.path.split("eps_bucket=")[1].split("/")[0])
            if 1 in classes and splits[bucket + 1] <= state["low_water"] or -1 in classes and splits[bucket] >= state["high_water"]:
                continue
            parts.append(Part(info.path, "base", bucket))
        overlay = f"{version}/overlay/round={state['round']}"
        for info in files.get_file_info(pafs.FileSelector(overlay, recursive=True, allow_not_found=True)):
            if info.path.endswith(".parquet"):
                parts.append(Part(info.path, "overlay", -1))
        return parts

    def read(self, part: Part) -> Iterator[pa.RecordBatch]:
        state = self._manifest()
        files, _ = _open(self.path)
        low, high = state["low_water"], state["high_water"]
        names = ["id", "eps"] if part.kind == "base" else ["id", "eps", "class"]
        data = ds.dataset(part.file, filesystem=files, format="parquet", partitioning=None)
        keep = None
        for name, kind, value in self.filters:
            if name == "class" and part.kind == "base":
                continue
            f = ds.field(name)
            test = {"eq": lambda f=f, v=value: f == v, "in": lambda f=f, v=value: f.isin(list(v)), "ge": lambda f=f, v=value: f >= v, "lt": lambda f=f, v=value: f < v}[kind]()
            keep = test if keep is None else keep & test
        for batch in data.to_batches(columns=names, filter=keep):
            if part.kind == "base":
                eps = batch.column("eps")
                outside = pc.or_(pc.greater_equal(eps, high), pc.less(eps, low))
                batch = batch.filter(outside)
                cls = pa.array([1 if e >= high else -1 for e in batch.column("eps").to_pylist()], pa.int32())
                batch = pa.RecordBatch.from_arrays([batch.column("id"), cls, batch.column("eps")], ["id", "class", "eps"])
                for name, kind, value in self.filters:
                    if name == "class":
                        wanted = pa.array([value] if kind == "eq" else list(value), pa.int32()) if kind in ("eq", "in") else None
                        batch = batch.filter(pc.is_in(batch.column("class"), wanted)) if wanted is not None else batch.filter((pc.greater_equal if kind == "ge" else pc.less)(batch.column("class"), value))
            else:
                batch = batch.select(["id", "class", "eps"])
            if batch.num_rows:
                yield batch


class ViewSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "modelview"

    def schema(self) -> str:
        return "id long, class int, eps double"

    def reader(self, schema: object) -> ViewReader:
        return ViewReader(self.options["path"])


def register(spark: SparkSession) -> None:
    ship(spark)
    spark.conf.set("spark.sql.python.filterPushdown.enabled", "true")
    spark.dataSource.register(ViewSource)
