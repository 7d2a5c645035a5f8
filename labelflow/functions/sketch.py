"""Count-min sketches of (key, value) rows as column arithmetic.

A sketch has ``depth`` rows of ``width`` cells; key i adds its value to cell ((a i + b) mod p) mod width of each row,
under that row's a and b. In the *cells* layout a sketch is rows (by..., cell, val) with cell = row * width + column
and zero cells absent; in the *block* layout one array of depth * width doubles for each group. Encoding is linear, so
sums and multiples of sketches are sketches of sums and multiples. An estimate is the least of a key's cells and is
never below the true value for non-negative values.
"""

from __future__ import annotations

import hashlib
import json
import random
from dataclasses import dataclass
from functools import reduce

from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PRIME = 2**31 - 1


@dataclass(frozen=True)
class SketchSpec:
    """Shape and hash functions; two sketches can be combined only if their specs are equal."""

    width: int
    depth: int
    seed: int
    prime: int
    a: tuple[int, ...]
    b: tuple[int, ...]

    @staticmethod
    def create(width: int, depth: int, seed: int = 42) -> "SketchSpec":
        if width < 1 or depth < 1:
            raise ValueError("a sketch needs a width and a depth of at least 1")
        draw = random.Random(seed)
        pairs = [(draw.randrange(1, PRIME), draw.randrange(PRIME)) for _ in range(depth)]
        return SketchSpec(width, depth, seed, PRIME, tuple(a for a, _ in pairs), tuple(b for _, b in pairs))

    @property
    def cells(self) -> int:
        return self.width * self.depth

    def as_dict(self) -> dict:
        return {"width": self.width, "depth": self.depth, "seed": self.seed, "prime": self.prime, "a": list(self.a), "b": list(self.b)}

    @staticmethod
    def from_dict(d: dict) -> "SketchSpec":
        return SketchSpec(d["width"], d["depth"], d["seed"], d["prime"], tuple(d["a"]), tuple(d["b"]))

    def fingerprint(self) -> str:
        return hashlib.sha256(json.dumps(self.as_dict(), sort_keys=True).encode()).hexdigest()[:16]

    def assert_same(self, other: "SketchSpec") -> None:
        if self != other:
            raise ValueError("sketches of different shape or hash functions can't be combined")

    def cell_index(self, key: int, row: int) -> int:
        return row * self.width + (self.a[row] * key + self.b[row]) % self.prime % self.width

    def row(self, row: int) -> "SketchSpec":
        """The spec of one row alone."""
        return SketchSpec(self.width, 1, self.seed, self.prime, (self.a[row],), (self.b[row],))


def linear_hash(key: Column, spec: SketchSpec, row: int) -> Column:
    """The cell of ``key`` in a row. Keys must lie in [0, p), so that products stay below 2^62; others raise."""
    key = key.cast("long")
    key = F.when((key < 0) | (key >= spec.prime), F.raise_error(F.lit(f"keys of a sketch must lie in [0, {spec.prime})")).cast("long")).otherwise(key)
    return ((key * F.lit(spec.a[row]) + F.lit(spec.b[row])) % F.lit(spec.prime) % F.lit(spec.width) + F.lit(row * spec.width)).cast("int")


def cells_of(key: Column, spec: SketchSpec) -> Column:
    return F.array(*[linear_hash(key, spec, j) for j in range(spec.depth)])


def empty_sketch(spark: SparkSession, spec: SketchSpec, by: str = "node bigint", layout: str = "cells") -> DataFrame:
    """No cells; as a block, one all-zero sketch of node 0."""
    if layout == "cells":
        return spark.createDataFrame([], f"{by}, cell int, val double")
    return spark.range(1).select(F.col("id").alias(by.split()[0]), F.array_repeat(F.lit(0.0), spec.cells).alias("s"))


def encode(df: DataFrame, key: str, val: str, by: list[str], spec: SketchSpec, layout: str = "cells") -> DataFrame:
    """The sketch of (key, value) rows for each group; sums are combined before the shuffle."""
    spread = df.select(*by, F.explode(cells_of(F.col(key), spec)).alias("cell"), F.col(val).cast("double").alias("val"))
    cells = spread.groupBy(*by, "cell").agg(F.sum("val").alias("val")).filter("val != 0")
    return cells if layout == "cells" else to_block(cells, by, spec)


def estimate(sketch: DataFrame, pairs: DataFrame, key: str, by: list[str], spec: SketchSpec) -> DataFrame:
    """by..., key, estimate for each requested pair of a group and a key; absent cells are 0."""
    wanted = pairs.select(*by, key, F.explode(cells_of(F.col(key), spec)).alias("cell"))
    found = wanted.join(sketch.select(*by, "cell", "val"), [*by, "cell"], "left")
    return found.groupBy(*by, key).agg(F.min(F.coalesce("val", F.lit(0.0))).alias("estimate"))


def estimate_block(block: Column, key: Column, spec: SketchSpec) -> Column:
    """The estimate from an array sketch."""
    return F.array_min(F.transform(cells_of(key, spec), lambda c: F.element_at(block, c + 1)))


def estimate_arrays(blocks: DataFrame, pairs: DataFrame, key: str, by: list[str], spec: SketchSpec) -> DataFrame:
    """As :func:`estimate`, from array sketches (by..., s)."""
    met = pairs.select(*by, key).distinct().join(blocks.select(*by, "s"), by, "left")
    return met.select(*by, key, F.coalesce(estimate_block(F.col("s"), F.col(key), spec), F.lit(0.0)).alias("estimate"))


def combine(parts: list[tuple[float, DataFrame]], by: list[str]) -> DataFrame:
    """The linear combination of sketches (cells) of one spec."""
    scaled = [s.select(*by, "cell", (F.col("val") * F.lit(float(c))).alias("val")) for c, s in parts]
    return reduce(DataFrame.unionByName, scaled).groupBy(*by, "cell").agg(F.sum("val").alias("val")).filter("val != 0")


def combine_blocks(a: Column, b: Column, x: float, y: float) -> Column:
    return F.zip_with(a, b, lambda p, q: p * F.lit(float(x)) + q * F.lit(float(y)))


def weighted_sum(sketch: DataFrame, by: list[str], weight: str) -> DataFrame:
    """The sum of sketches (cells with a weight column) for each group."""
    return sketch.groupBy(*by, "cell").agg(F.sum(F.col(weight) * F.col("val")).alias("val")).filter("val != 0")


def to_block(cells: DataFrame, by: list[str], spec: SketchSpec) -> DataFrame:
    """Cells as one array for each group (of a size fixed by the spec)."""
    grouped = cells.groupBy(*by).agg(F.map_from_entries(F.collect_list(F.struct("cell", "val"))).alias("m"))
    return grouped.select(*by, F.transform(F.sequence(F.lit(0), F.lit(spec.cells - 1)), lambda c: F.coalesce(F.try_element_at("m", c), F.lit(0.0))).alias("s"))


def to_cells(blocks: DataFrame, by: list[str]) -> DataFrame:
    return blocks.select(*by, F.posexplode("s").alias("cell", "val")).filter("val != 0")


def row_mass(sketch: DataFrame, by: list[str], spec: SketchSpec) -> DataFrame:
    """The sum of each row: the L1 norm of a non-negative vector, the same for all rows."""
    row = F.floor(F.col("cell") / spec.width).cast("int")
    return sketch.groupBy(*by, row.alias("row")).agg(F.sum("val").alias("mass"))


def builtin_counts(df: DataFrame, key: str, eps: float, confidence: float, seed: int) -> DataFrame:
    """Spark's own integer count-min sketch, for contrast: it counts only and can't be scaled."""
    return df.agg(F.count_min_sketch(F.col(key), F.lit(eps), F.lit(confidence), F.lit(seed)).alias("sketch"))
