"""Write a layout as Parquet, a folder for each partition or for several small ones, with a manifest beside it; read it back and query it."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import dataclass

from pyspark.sql import Column, DataFrame, SparkSession, Window
from pyspark.sql import functions as F
from pyspark.sql.types import IntegerType, StructField, StructType

from evenbox.functions import geom
from evenbox.functions.curves import lattice, z_key
from evenbox.operators import quality
from evenbox.operators.meeting import CellGrid
from evenbox.operators.router import route
from evenbox.plans.baselines import CurveLayout
from evenbox.plans.grow import Layout


#: bytes that share a folder: partitions smaller than that are written together, sorted, so that neither tasks nor files are one for each
FOLDER = 8 << 20
#: bytes of a row group at least
ROW_GROUP = 1 << 20
#: pairs of queries and partitions, some 60 bytes each, that are sent to every task rather than shuffled with the records
SENT_PAIRS = 100_000


def write_index(df: DataFrame, layout: Layout | CurveLayout, path: str, axes: Sequence[str] = ("x", "y"), block: int = 128 << 20) -> Index:
    """Route, shuffle once so that a partition is in one task, sort each along a curve for row-group skipping, and write."""
    routed = route(df, layout, axes, "arrow")
    per = max(1, FOLDER // block)
    folders = -(-layout.parts // per) + 1  # and the one for records without a place
    low, high = layout.extent(len(axes))
    near = z_key([lattice(F.col(a), lo, hi, 12) for a, lo, hi in zip(axes, low, high, strict=True)], 12) if len(axes) < 6 else F.col(axes[0])
    folder = F.floor(F.col("part_id") / per).cast("int")
    placed = routed.withColumns({"folder": folder, "_near": near}).repartitionById(folders, F.col("folder") + 1).sortWithinPartitions("folder", "part_id", "_near").drop("_near")
    placed.write.mode("overwrite").option("parquet.block.size", max(block, ROW_GROUP)).partitionBy("folder").parquet(f"{path}/data")
    index = Index(df.sparkSession, path, tuple(axes), StructType([*df.schema.fields, StructField("part_id", IntegerType()), StructField("folder", IntegerType())]))
    quality.manifest(index.data(), axes, block).withColumn("folder", folder).write.mode("overwrite").parquet(f"{path}/manifest")
    return index


@dataclass
class Index:
    spark: SparkSession
    path: str
    axes: tuple[str, ...] = ("x", "y")
    #: of the stored records; left out, it is read from the files
    schema: StructType | None = None

    def data(self) -> DataFrame:
        return self._stored().drop("folder")

    def _stored(self) -> DataFrame:
        reader = self.spark.read
        return (reader.schema(self.schema) if self.schema else reader).parquet(f"{self.path}/data")

    def _parts(self, ids: list[int], folders: dict[int, int]) -> DataFrame:
        """The records of some partitions: folders are pruned, in them row groups."""
        held = self._stored().where(F.col("folder").isin(sorted({folders[i] for i in ids}))).where(F.col("part_id").isin(ids))
        return held.drop("folder")

    def manifest(self) -> DataFrame:
        return self.spark.read.parquet(f"{self.path}/manifest")

    def _inside(self, lo: Sequence[float], hi: Sequence[float]) -> Column:
        return geom.every([F.col(a).between(low, high) for a, low, high in zip(self.axes, lo, hi, strict=True)])

    def classify(self, lo: Sequence[float], hi: Sequence[float]) -> tuple[list[int], list[int]]:
        """(contained, boundary) partitions of a query box: a row for each partition that it meets comes to the driver."""
        return self._classified(lo, hi)[:2]

    def _classified(self, lo: Sequence[float], hi: Sequence[float]) -> tuple[list[int], list[int], dict[int, int]]:
        """The same, and the folders of them all."""
        ends = quality._ends(self.axes)
        box = [F.lit(float(x)) for x in lo], [F.lit(float(x)) for x in hi]
        met = self.manifest().where(geom.overlaps(*ends, *box)).select("part_id", "folder", geom.contains(*box, *ends).alias("inside")).collect()
        return [r["part_id"] for r in met if r["inside"]], [r["part_id"] for r in met if not r["inside"]], {r["part_id"]: r["folder"] for r in met}

    def range(self, lo: Sequence[float], hi: Sequence[float]) -> DataFrame:
        """Records in a box. Contained partitions are read without a test, boundary partitions with predicates that reach the row groups, others not at all."""
        contained, boundary, folders = self._classified(lo, hi)
        return self._parts(contained, folders).unionByName(self._parts(boundary, folders).where(self._inside(lo, hi)))

    def range_count(self, lo: Sequence[float], hi: Sequence[float]) -> DataFrame:
        """The number of records in a box; contained partitions are counted from the manifest."""
        ends = quality._ends(self.axes)
        box = [F.lit(float(x)) for x in lo], [F.lit(float(x)) for x in hi]
        _, boundary, folders = self._classified(lo, hi)
        known = self.manifest().where(geom.overlaps(*ends, *box) & geom.contains(*box, *ends)).agg(F.coalesce(F.sum("n_rows"), F.lit(0)).alias("n"))
        read = self._parts(boundary, folders).where(self._inside(lo, hi)).agg(F.count("*").alias("n"))
        return known.unionByName(read).agg(F.sum("n").alias("n"))

    def range_batch(self, queries: DataFrame) -> DataFrame:
        """(qid, record) of many query boxes (qlo_/qhi_ columns) in one scan of the partitions they touch."""
        qlo, qhi = [F.col(f"qlo_{a}") for a in self.axes], [F.col(f"qhi_{a}") for a in self.axes]
        met = quality._asked(queries, self.manifest(), self.axes).select(*queries.columns, F.col("part_id").alias("_part"), geom.contains(qlo, qhi, *quality._ends(self.axes)).alias("_inside"))
        data = self.data()
        inside = F.col("_inside") | geom.every([F.col(a).between(low, high) for a, low, high in zip(self.axes, qlo, qhi, strict=True)])
        # the pairs of queries and partitions grow with both; the stored records are shuffled for them only if they are many
        if met.limit(SENT_PAIRS + 1).count() <= SENT_PAIRS:
            met = F.broadcast(met)
        return data.join(met, F.col("part_id") == F.col("_part")).where(inside).select("qid", *data.columns)

    def knn(self, queries: DataFrame, k: int, keys: Sequence[str]) -> DataFrame:
        """The k records nearest to each query point (columns q_<axis>), ties by key.

        Round one: the partitions that share the query's cell of a grid over the manifest give a radius, from the k-th record they have. Queries whose
        cell has fewer records take partitions in order of distance until they hold k. Round two: every partition within the radius, found by cells too.
        """
        at = [F.col(f"q_{a}") for a in self.axes]
        ends = quality._ends(self.axes)
        names = [f"lo_{a}" for a in self.axes], [f"hi_{a}" for a in self.axes]
        man = self.manifest().select("part_id", "n_rows", *names[0], *names[1])
        grid = CellGrid(man, *names)
        held = grid.dealt(man, *names, "b")
        gap = geom.gap_squared(*ends, at)
        data = self.data()
        far = geom.distance_squared([F.col(a) for a in self.axes], at)
        rank = Window.partitionBy("qid").orderBy("d2", *keys)

        def nearest(parts: DataFrame) -> DataFrame:
            found = data.join(parts.select(*queries.columns, F.col("part_id").alias("_part")), F.col("part_id") == F.col("_part"))
            return found.withColumn("d2", far).withColumn("rank", F.row_number().over(rank)).where(F.col("rank") <= k)

        home = grid.dealt(queries, at, at, "a").join(held, grid.same_cells()).select(*queries.columns, "part_id").distinct()
        radius = nearest(home).where(F.col("rank") == k).select("qid", F.col("d2").alias("_radius"))
        ahead = Window.partitionBy("qid").orderBy("_gap", "part_id").rowsBetween(Window.unboundedPreceding, -1)
        gaps = queries.join(radius, "qid", "left_anti").crossJoin(man).withColumn("_gap", gap)
        near = gaps.withColumn("_before", F.coalesce(F.sum("n_rows").over(ahead), F.lit(0))).where(F.col("_before") < k)
        radius = radius.unionByName(nearest(near).groupBy("qid").agg(F.max("d2").alias("_radius")))
        around = queries.join(radius, "qid")
        reach = F.sqrt("_radius") * (1 + 1e-9)
        within = grid.dealt(around, [c - reach for c in at], [c + reach for c in at], "a").join(held, grid.same_cells()).where(gap <= F.col("_radius"))
        return nearest(within.select(*queries.columns, "part_id").distinct()).select("qid", *keys, "d2", "rank")


def grid_queries(spark: SparkSession, low: Sequence[float], high: Sequence[float], n: int, fraction: float, axes: Sequence[str] = ("x", "y")) -> DataFrame:
    """n equal boxes, each ``fraction`` of the extent's volume, on a regular grid of places."""
    d = len(axes)
    side = fraction ** (1 / d)
    each = max(1, int(round(n ** (1 / d))))
    rows = spark.range(n).withColumnRenamed("id", "qid")
    columns = {}
    for i, (a, lo, hi) in enumerate(zip(axes, low, high, strict=True)):
        step = F.pmod(F.floor(F.col("qid") / each**i), F.lit(each)) if i < d - 1 else F.floor(F.col("qid") / each**i)
        start = lo + (hi - lo) * (1 - side) * (step + 0.5) / max(each, -(-n // each ** (d - 1)))
        columns |= {f"qlo_{a}": start, f"qhi_{a}": start + (hi - lo) * side}
    return rows.withColumns(columns)
