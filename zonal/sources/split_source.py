"""A data source that reads splits: partitions are (chunk, tile range) splits, rows partials.

``spark.read.format("zonal_splits").option("tiles", ..).option("store", ..)`` plans from the
store's footer alone, prunes untouched tiles, and every partition reads its tile range and its
chunk's runs side by side, giving one partial row a zone. Paths are anything pyarrow opens.
"""

from __future__ import annotations

from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import pyarrow.dataset as ds
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql.datasource import DataSource, DataSourceReader, InputPartition

from ..functions.accumulate import DEFAULT, is_whole, merge_partials, sum_type
from ..functions.grid import RasterLayer


class Split(InputPartition):
    def __init__(self, chunk: int, lo: int, hi: int):
        self.chunk, self.lo, self.hi = chunk, lo, hi


def _open(uri: str) -> ds.Dataset:
    from pyarrow import fs

    store, path = fs.FileSystem.from_uri(uri) if "://" in uri or uri.startswith("file:") else (fs.LocalFileSystem(), uri)
    return ds.dataset(path, filesystem=store, format="parquet", partitioning="hive")


class ZonalSplitReader(DataSourceReader):
    def __init__(self, options: dict):
        self.tiles, self.store = options["tiles"], options["store"]
        self.tile_w, self.tile_h, self.tiles_x = (int(options[k]) for k in ("tile_w", "tile_h", "tiles_x"))
        self.per_split = int(options.get("tiles_per_split", "64"))
        self.per_file = int(options.get("tiles_per_file", "0"))
        self.real = options.get("real", "no") == "yes"

    def partitions(self) -> list[Split]:
        """Footers only: consecutive touched tiles of a chunk, some tiles a split, of one file
        of the raster if its files hold a known number of tiles."""
        foot = _open(f"{self.store}/footer").to_table(columns=["chunk_id", "tile_id"]).sort_by([("chunk_id", "ascending"), ("tile_id", "ascending")])
        chunk, tile = foot["chunk_id"].to_numpy(), foot["tile_id"].to_numpy()
        out, begin = [], 0
        for i in range(1, len(tile) + 1):
            other_file = i < len(tile) and self.per_file and tile[i] // self.per_file != tile[begin] // self.per_file
            if i == len(tile) or chunk[i] != chunk[begin] or tile[i] != tile[i - 1] + 1 or i - begin == self.per_split or other_file:
                out.append(Split(int(chunk[begin]), int(tile[begin]), int(tile[i - 1])))
                begin = i
        return out

    def read(self, partition: Split) -> Iterator[pa.RecordBatch]:
        span = (pc.field("tile_id") >= partition.lo) & (pc.field("tile_id") <= partition.hi)
        runs = _open(f"{self.store}/runs").to_table(filter=(pc.field("chunk_id") == partition.chunk) & span, columns=["zone_id", "tile_id", "y", "x0", "x1"]).sort_by("tile_id")
        tiles = _open(self.tiles).to_table(filter=span, columns=["tile_id", "values"]).sort_by("tile_id")
        zone, of, y, x0, x1 = (runs[c].to_numpy() for c in ("zone_id", "tile_id", "y", "x0", "x1"))
        total: dict[int, list] = {}
        number = float if self.real else int
        for tile, cell in zip(tiles["tile_id"].to_pylist(), tiles["values"], strict=True):
            lo, hi = np.searchsorted(of, tile), np.searchsorted(of, tile, "right")
            if lo == hi:
                continue
            flat = cell.values
            valid = pc.is_valid(flat).to_numpy(zero_copy_only=False)
            v = pc.fill_null(flat, 0).to_numpy(zero_copy_only=False)
            row, col = tile // self.tiles_x * self.tile_h, tile % self.tiles_x * self.tile_w
            for i in range(lo, hi):
                a = (int(y[i]) - row) * self.tile_w + int(x0[i]) - col
                part = v[a : a + int(x1[i] - x0[i])][valid[a : a + int(x1[i] - x0[i])]]
                if len(part):
                    low, high = number(part.min()), number(part.max())
                    t = total.setdefault(int(zone[i]), [0, number(0), low, high])
                    t[0] += len(part)
                    t[1] += number(part.sum(dtype=np.float64 if self.real else np.int64))
                    t[2], t[3] = min(t[2], low), max(t[3], high)
        value = pa.float64() if self.real else pa.int64()
        cols = [list(total), *([t[k] for t in total.values()] for k in range(4))]
        kinds = [pa.int64(), pa.int64(), value, value, value]
        yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], ["zone_id", "cnt", "sum_v", "min_v", "max_v"])


class ZonalSplitSource(DataSource):
    @classmethod
    def name(cls) -> str:
        return "zonal_splits"

    def schema(self) -> str:
        value = "double" if self.options.get("real", "no") == "yes" else "bigint"
        return f"zone_id bigint, cnt bigint, sum_v {value}, min_v {value}, max_v {value}"

    def reader(self, schema) -> ZonalSplitReader:
        return ZonalSplitReader(self.options)


def zonal_from_store(spark: SparkSession, raster: RasterLayer, store: str, tiles_per_split: int = 64, one_file: bool = True, aggs: tuple[str, ...] = DEFAULT, wide: bool = False) -> DataFrame:
    """Aggregates per zone from a written tile table and a written crossing store."""
    meta, kind = raster.meta, raster.df.schema["values"].dataType.elementType
    if sum_type(kind) not in ("bigint", "double"):
        raise ValueError("splits add up whole numbers and doubles, not decimals")
    spark.dataSource.register(ZonalSplitSource)
    options = {
        "tiles": raster.path, "store": store, "tile_w": meta.tile_w, "tile_h": meta.tile_h, "tiles_x": meta.tiles_x, "tiles_per_split": tiles_per_split,
        "tiles_per_file": (raster.tiles_per_group or 0) if one_file else 0, "real": "no" if is_whole(kind) else "yes",
    }
    return merge_partials(spark.read.format("zonal_splits").options(**{k: str(v) for k, v in options.items()}).load(), ["zone_id"], aggs, wide)
