"""Grids, quantisation, curve histograms and the end-to-end encoding."""

from __future__ import annotations

import math
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import curves
from . import descriptors, geometry


@dataclass(frozen=True)
class DimSpec:
    """One dimension: half-open bins between lo and hi, the last one closed."""

    name: str
    lo: float
    hi: float
    bits: int = 4

    def cell(self) -> Column:
        top = (1 << self.bits) - 1
        span = self.hi - self.lo if self.hi > self.lo else 1.0
        scaled = F.floor(F.round((F.col(self.name) - F.lit(self.lo)) / F.lit(span) * F.lit(float(1 << self.bits)), 9))
        return F.greatest(F.lit(0), F.least(scaled, F.lit(top))).cast("int")


@dataclass(frozen=True)
class GridSpec:
    dims: tuple[DimSpec, ...]

    @property
    def size(self) -> int:
        return 1 << sum(d.bits for d in self.dims)


def spherical_grid(bits: int = 4, radius: float = 60.0, descriptor: tuple[float, float] | None = None) -> GridSpec:
    """Descriptor, distance, polar angle and azimuth; integer descriptors map to themselves."""
    lo, hi = descriptor or (0.0, float(1 << bits))
    return GridSpec((DimSpec("descriptor", lo, hi, bits), DimSpec("r", 0.0, radius, bits), DimSpec("polar", 0.0, math.pi, bits), DimSpec("azimuth", -math.pi, math.pi, bits)))


def quantize(df: DataFrame, spec: GridSpec) -> DataFrame:
    """Adds ``q0, q1, ...``; values are rounded to 9 decimals of a bin first, so engines agree at edges."""
    return df.withColumns({f"q{i}": d.cell() for i, d in enumerate(spec.dims)})


def fit_ranges(df: DataFrame, column: str, how: str = "minmax") -> tuple[float, float]:
    """Range of a column: its extremes or its 1 % and 99 % quantiles; two numbers come to the driver."""
    if how == "minmax":
        r = df.agg(F.min(column).alias("lo"), F.max(column).alias("hi")).first()
    else:
        r = df.agg(F.percentile_approx(column, F.lit(0.01), 10000).alias("lo"), F.percentile_approx(column, F.lit(0.99), 10000).alias("hi")).first()
    return float(r.lo or 0.0), float(r.hi if r.hi is not None else 1.0)


def within_sphere(df: DataFrame, radius: float = 60.0) -> DataFrame:
    return df.where(F.col("r") <= radius)


@dataclass(frozen=True)
class EncodeConfig:
    """descriptor: atomic_number, coordination, coulomb or custom; outside: drop or clamp."""

    descriptor: str = "atomic_number"
    bits: int = 4
    radius: float = 60.0
    center: str = "mass"
    outside: str = "drop"
    curve: str = "morton"
    ranges: str = "minmax"
    range_value: tuple[float, float] | None = None
    options: dict = field(default_factory=dict)


def spherical_atoms(atoms: DataFrame, config: EncodeConfig = EncodeConfig()) -> DataFrame:
    """Atoms with descriptor and canonical spherical coordinates."""
    described = descriptors.REGISTRY[config.descriptor](atoms, **config.options)
    return geometry.to_spherical(geometry.pose(described, config.center))


def encoded_atoms(atoms: DataFrame, config: EncodeConfig = EncodeConfig()) -> DataFrame:
    """``structure_id, ..., cell``: every atom's index on the curve."""
    return indexed_atoms(spherical_atoms(atoms, config), config)


def indexed_atoms(s: DataFrame, config: EncodeConfig = EncodeConfig()) -> DataFrame:
    """The same from described spherical atoms, which configurations that differ in grid or curve alone can share."""
    s = within_sphere(s, config.radius) if config.outside == "drop" else s
    span = config.range_value
    if config.descriptor in ("coulomb", "custom") and span is None:
        span = fit_ranges(s, "descriptor", config.ranges)
    q = quantize(s, spherical_grid(config.bits, config.radius, span))
    cols = ["q0", "q1", "q2", "q3"]
    if config.curve == "hilbert":
        return curves.hilbert_encode(q, cols, config.bits, "cell")
    encode = {"morton": curves.morton_encode, "rowmajor": curves.rowmajor_encode}.get(config.curve)
    if config.curve == "peano":
        return q.withColumn("cell", curves.peano_encode(cols, math.ceil(config.bits * math.log(2) / math.log(3))))
    return q.withColumn("cell", encode(cols, config.bits))


def histogram(encoded: DataFrame) -> DataFrame:
    """``structure_id, cell, n``; atoms that are dealt by structure need no further shuffle."""
    return encoded.groupBy("structure_id", "cell").agg(F.count("*").alias("n"))


def encode_structures(atoms: DataFrame, config: EncodeConfig = EncodeConfig()) -> DataFrame:
    return histogram(encoded_atoms(atoms, config))


def to_sparse(triplets: DataFrame) -> DataFrame:
    """One row per structure: cells ascending with their counts, as arrays and as a map."""
    rows = triplets.groupBy("structure_id").agg(F.sort_array(F.collect_list(F.struct("cell", "n"))).alias("_e"))
    return rows.select("structure_id", F.col("_e.cell").alias("cells"), F.col("_e.n").alias("counts"), F.map_from_entries("_e").alias("bins"))


def traverse(triplets: DataFrame) -> DataFrame:
    """All bins in ascending order of the curve."""
    return triplets.repartitionByRange("cell").sortWithinPartitions("cell", "structure_id")
