"""Positions on the sphere as column expressions, and the same as SQL functions. No Python runs on executors, but in the
forms named libm: the JVM's sines differ from the C library's, which DuckDB calls, in a last bit now and then, and where a distance lies
on a radius, or a mean on half a last place, that bit decides."""

from __future__ import annotations

import math
from operator import mul

import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

PAD = 1e-9  # degrees by which boxes, never distances, are widened


def _c(x) -> Column:
    return F.col(x) if isinstance(x, str) else x if isinstance(x, Column) else F.lit(float(x))


def unit_vector(ra, dec) -> list[Column]:
    """x, y, z of a position in degrees."""
    a, d = F.radians(_c(ra)), F.radians(_c(dec))
    return [(F.cos(d) * F.cos(a)).alias("x"), (F.cos(d) * F.sin(a)).alias("y"), F.sin(d).alias("z")]


def _libm(f, *columns) -> Column:
    """f of lists of doubles, by the C library; null where an argument is."""
    def each(*arrays: pa.Array) -> pa.Array:
        out = pa.array(f(*[a.fill_null(0.0).to_pylist() for a in arrays]), pa.float64())
        for a in arrays:
            out = pc.if_else(a.is_valid(), out, None) if a.null_count else out
        return out

    return F.arrow_udf(each, "double")(*columns)


def unit_vector_libm(ra, dec) -> list[Column]:
    a, d = F.radians(_c(ra)), F.radians(_c(dec))
    x, y = (lambda a, d, g=g: list(map(mul, map(math.cos, d), map(g, a))) for g in (math.cos, math.sin))
    return [_libm(x, a, d).alias("x"), _libm(y, a, d).alias("y"), _libm(lambda d: list(map(math.sin, d)), d).alias("z")]


def radec_libm(x, y, z) -> list[Column]:
    x, y, z = _c(x), _c(y), _c(z)
    turn = lambda a, b: list(map(math.degrees, map(math.atan2, a, b)))
    return [F.pmod(_libm(turn, y, x), F.lit(360.0)).alias("ra_deg"), _libm(turn, z, F.sqrt(x * x + y * y)).alias("dec_deg")]


def radec(x, y, z) -> list[Column]:
    """Degrees of a vector of any length but 0; right ascension in [0, 360)."""
    x, y, z = _c(x), _c(y), _c(z)
    return [F.pmod(F.degrees(F.atan2(y, x)), F.lit(360.0)).alias("ra_deg"), F.degrees(F.atan2(z, F.sqrt(x * x + y * y))).alias("dec_deg")]


def strip_of(dec, width: float = 1.0) -> Column:
    return F.floor(_c(dec) / F.lit(float(width))).cast("int")


def strips_touched(dec, r_deg, width: float = 1.0) -> Column:
    """All strips within r of a declination, as an array."""
    reach = _c(r_deg) + PAD
    return F.sequence(strip_of(F.greatest(_c(dec) - reach, F.lit(-90.0)), width), strip_of(F.least(_c(dec) + reach, F.lit(90.0)), width))


def ra_halfwidth(dec, r_deg) -> Column:
    """Half-width in right ascension of a circle of radius r: all the way round where it holds a pole."""
    d, r = _c(dec), _c(r_deg)
    ratio = F.sin(F.radians(r)) / F.cos(F.radians(d))
    return F.when(F.abs(d) + r < 90.0, F.degrees(F.asin(F.least(ratio, F.lit(1.0))))).otherwise(F.lit(180.0))


def ra_gap(a, b) -> Column:
    """The circular difference of two right ascensions."""
    return F.abs(F.pmod(_c(a) - _c(b) + 540.0, F.lit(360.0)) - 180.0)


def chord2(ax, ay, az, bx, by, bz) -> Column:
    dx, dy, dz = _c(ax) - _c(bx), _c(ay) - _c(by), _c(az) - _c(bz)
    return dx * dx + dy * dy + dz * dz


def sep_arcsec(d2) -> Column:
    """Arc of a squared chord, by the half-angle."""
    return F.degrees(2 * F.asin(F.least(F.sqrt(_c(d2)) / 2, F.lit(1.0)))) * 3600.0


def rounded(x, places: int) -> Column:
    """x to so many places, halves away from zero, worked out on the double as C and DuckDB do; `F.round` goes by the decimal text, slowly."""
    v = _c(x) * F.lit(10.0**places)
    return F.signum(v) * F.floor(F.abs(v) + 0.5) / F.lit(10.0**places)


def sep_dot(ax, ay, az, bx, by, bz) -> Column:
    """Arc from the dot product: poor at small angles; for comparison."""
    dot = _c(ax) * _c(bx) + _c(ay) * _c(by) + _c(az) * _c(bz)
    return F.degrees(F.acos(F.least(F.lit(1.0), F.greatest(F.lit(-1.0), dot)))) * 3600.0


def chord2_of(r_deg) -> Column:
    """The squared chord of an arc in degrees."""
    if isinstance(r_deg, float):
        return F.lit(4 * math.sin(math.radians(r_deg) / 2) ** 2)
    s = F.sin(F.radians(_c(r_deg)) / 2)
    return 4 * s * s


def position_angle(ra1, dec1, ra2, dec2) -> Column:
    """Direction from 1 to 2, degrees from north through east."""
    d = F.radians(_c(ra2) - _c(ra1))
    p, q = F.radians(_c(dec1)), F.radians(_c(dec2))
    return F.pmod(F.degrees(F.atan2(F.sin(d) * F.cos(q), F.cos(p) * F.sin(q) - F.sin(p) * F.cos(q) * F.cos(d))), F.lit(360.0))


def sexagesimal(deg, hours: bool = False) -> Column:
    """deg as text dd:mm:ss.sss, or hh:mm:ss.sss."""
    ms = F.round(F.abs(_c(deg)) / (15.0 if hours else 1.0) * 3_600_000).cast("long")
    sign = F.when(_c(deg) < 0, F.lit("-")).otherwise(F.lit(""))
    two = lambda x: F.lpad(x.cast("string"), 2, "0")
    return F.concat(sign, two(F.floor(ms / 3_600_000)), F.lit(":"), two(F.floor(ms / 60_000) % 60), F.lit(":"), two(F.floor(ms / 1000) % 60), F.lit("."), F.lpad((ms % 1000).cast("string"), 3, "0"))


def mjd_of(ts) -> Column:
    return F.lit(40587.0) + F.unix_micros(_c(ts)) / F.lit(86_400_000_000.0)


def with_position(df: DataFrame, width: float = 1.0, ra: str = "ra_deg", dec: str = "dec_deg", libm: bool = False) -> DataFrame:
    """Add x, y, z and strip."""
    return df.select("*", *(unit_vector_libm if libm else unit_vector)(ra, dec), strip_of(dec, width).alias("strip"))


_SQL = {
    "sky_ra_halfwidth(dec DOUBLE, r DOUBLE) RETURNS DOUBLE": "CASE WHEN abs(dec) + r < 90 THEN degrees(asin(least(sin(radians(r)) / cos(radians(dec)), 1D))) ELSE 180D END",
    "sky_strip(dec DOUBLE, width DOUBLE) RETURNS INT": "CAST(floor(dec / width) AS INT)",
    "sky_ra_gap(a DOUBLE, b DOUBLE) RETURNS DOUBLE": "abs(pmod(a - b + 540D, 360D) - 180D)",
    "sky_chord2(ra1 DOUBLE, dec1 DOUBLE, ra2 DOUBLE, dec2 DOUBLE) RETURNS DOUBLE": "power(cos(radians(dec1)) * cos(radians(ra1)) - cos(radians(dec2)) * cos(radians(ra2)), 2) + power(cos(radians(dec1)) * sin(radians(ra1)) - cos(radians(dec2)) * sin(radians(ra2)), 2) + power(sin(radians(dec1)) - sin(radians(dec2)), 2)",
    "sky_sep_arcsec(d2 DOUBLE) RETURNS DOUBLE": "degrees(2 * asin(least(sqrt(d2) / 2, 1D))) * 3600D",
}


def register(spark: SparkSession) -> list[str]:
    """Make the helpers callable from SQL; they are inlined into plans."""
    for head, body in _SQL.items():
        spark.sql(f"CREATE OR REPLACE TEMPORARY FUNCTION {head} RETURN {body}")
    return [h.split("(")[0] for h in _SQL]
