"""Sources and sinks of graphs: file formats, edge lists, and a generator as a data source."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from signpart import tables
from signpart.operators import graph


def round_trip(df: DataFrame, fmt: str, path: str | None = None) -> DataFrame:
    """df written in a format and read back with its own schema."""
    path = path or tables.shared_folder(df.sparkSession)
    df.write.mode("overwrite").format(fmt).save(path)
    return df.sparkSession.read.schema(df.schema).format(fmt).load(path)


def edge_list(spark: SparkSession, path: str) -> DataFrame:
    """Edges of a text file with lines "u v w"; lines that begin with # are remarks."""
    cells = F.split(F.trim("value"), r"\s+")
    rows = spark.read.text(path).where(~F.col("value").startswith("#") & (F.trim("value") != "")).select(cells.alias("c"))
    return graph.build(rows.select(F.get("c", F.lit(0)).cast("long").alias("u"), F.get("c", F.lit(1)).cast("long").alias("v"), F.get("c", F.lit(2)).cast("double").alias("w")))


def write_edges(edges: DataFrame, path: str, bands: int = 16) -> None:
    """Edges as Parquet in folders by decreasing |w|, so that a band is read alone."""
    cuts = edges.select(F.abs("w").alias("s")).stat.approxQuantile("s", [i / bands for i in range(1, bands)], 0.2 / bands)
    band = sum((F.abs("w") <= c).cast("int") for c in sorted(set(cuts)))
    edges.withColumn("band", band if cuts else F.lit(0)).repartition("band").sortWithinPartitions("u").write.mode("overwrite").partitionBy("band").parquet(path)


class _Rows(InputPartition):
    def __init__(self, first: int, last: int):
        super().__init__(first)
        self.first, self.last = first, last


class _PlantedReader(DataSourceReader):
    def __init__(self, height: int, width: int, cell: int):
        self.height, self.width, self.cell = height, width, cell

    def partitions(self):
        step = max(1, self.height // 16)
        return [_Rows(y, min(self.height, y + step)) for y in range(0, self.height, step)]

    def read(self, part):
        """The nearest of sites that stand off their lattice cells' corners by a fixed arithmetic."""

        def site(cy, cx):
            t = (cy * 73856093 + cx * 19349663) % 1000003
            return cy * self.cell + t % self.cell, cx * self.cell + (t // self.cell) % self.cell

        across = self.width // self.cell + 5
        for y in range(part.first, part.last):
            for x in range(self.width):
                near = min(((y - sy) ** 2 + (x - sx) ** 2, (cy + 2) * across + cx + 2) for cy in range(y // self.cell - 2, y // self.cell + 3) for cx in range(x // self.cell - 2, x // self.cell + 3) for sy, sx in (site(cy, cx),))
                yield (y * self.width + x, 0, y, x, near[1])


class PlantedRaster(DataSource):
    """spark.read.format("planted_raster").option("height", …).option("width", …): pixels with a true label."""

    @classmethod
    def name(cls) -> str:
        return "planted_raster"

    def schema(self) -> str:
        return "pix long, z long, y long, x long, gt long"

    def reader(self, schema):
        o = self.options
        return _PlantedReader(int(o.get("height", 64)), int(o.get("width", 64)), int(o.get("cell", 12)))


def register(spark: SparkSession) -> None:
    spark.dataSource.register(PlantedRaster)
