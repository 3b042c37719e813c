"""Work folders, text geometry, and other formats in and out."""

from __future__ import annotations

import tempfile
import uuid

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition


def work_path(spark: SparkSession, label: str) -> str:
    """A fresh folder: in the cluster's shared checkpoint folder, or in a temporary one where none is set."""
    root = spark.sparkContext.getConf().get("spark.checkpoint.dir") or spark.conf.get("spark.checkpoint.dir", None)
    return f"{root or 'file://' + tempfile.mkdtemp(prefix='evenbox-')}/{label}-{uuid.uuid4().hex[:12]}"


def point_wkt(x: Column, y: Column) -> Column:
    return F.concat(F.lit("POINT ("), x.cast("string"), F.lit(" "), y.cast("string"), F.lit(")"))


def parse_point(wkt: Column) -> tuple[Column, Column]:
    """x and y of a POINT text; null where it is none."""
    number = r"(-?[0-9.]+(?:[eE][-+]?[0-9]+)?)"
    part = lambda k: F.expr("null").cast("double") if k < 0 else F.nullif(F.regexp_extract(wkt, rf"^\s*POINT\s*\(\s*{number}\s+{number}\s*\)\s*$", k), F.lit("")).cast("double")
    return part(1), part(2)


def ring_box(wkt: Column) -> tuple[Column, Column, Column, Column]:
    """The box of a POLYGON or LINESTRING text of one ring."""
    pairs = F.split(F.regexp_extract(wkt, r"\(+([^()]+)\)+", 1), r"\s*,\s*")
    axis = lambda i: F.transform(pairs, lambda p: F.element_at(F.split(F.trim(p), r"\s+"), i + 1).cast("double"))
    return F.array_min(axis(0)), F.array_min(axis(1)), F.array_max(axis(0)), F.array_max(axis(1))


class DiagonalSource(DataSource):
    """Points near the diagonal of the unit cube: options d, rows, perc, buf (all optional)."""

    @classmethod
    def name(cls) -> str:
        return "evenbox_diagonal"

    def schema(self) -> str:
        return "id long, c array<double>"

    def reader(self, schema) -> DiagonalReader:
        return DiagonalReader(self.options)


class DiagonalReader(DataSourceReader):
    def __init__(self, options):
        self.d, self.rows = int(options.get("d", 3)), int(options.get("rows", 1000))
        self.perc, self.buf = float(options.get("perc", 0.05)), float(options.get("buf", 0.1))

    def partitions(self):
        step = max(1, -(-self.rows // 8))
        return [InputPartition((a, min(a + step, self.rows))) for a in range(0, self.rows, step)]

    def read(self, partition):
        import numpy as np

        for i in range(*partition.value):
            random = np.random.default_rng(i)
            u = random.random()
            on = random.random() < self.perc
            noise = np.zeros(self.d) if on else (random.random(self.d) - 0.5) * self.buf
            yield i, np.clip(u + noise, 0, 1).tolist()


def write_formats(df: DataFrame, path: str) -> dict[str, str]:
    """``df`` as csv, json lines, orc and parquet below ``path``."""
    paths = {kind: f"{path}/{kind}" for kind in ("csv", "json", "orc", "parquet")}
    for kind, at in paths.items():
        writer = df.write.mode("overwrite")
        (writer.option("header", True) if kind == "csv" else writer).format(kind).save(at)
    return paths
