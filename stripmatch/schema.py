"""Fixed schemas of the engine's tables, checked at ingest."""

from __future__ import annotations

from pyspark.sql import DataFrame
from pyspark.sql.types import BooleanType, DoubleType, IntegerType, LongType, StringType, StructField, StructType

_TYPES = {"int": IntegerType(), "long": LongType(), "double": DoubleType(), "string": StringType(), "boolean": BooleanType()}


def fields(text: str) -> StructType:
    """A schema of plain types; unlike the DDL parser it needs no session."""
    return StructType([StructField(n, _TYPES[t]) for n, t in (f.split() for f in text.split(","))])


DETECTION = fields("image_id int, source_id long, ra_deg double, dec_deg double, mjd double, flux double, flux_err double, ellipticity double, area double, band string, quality string")
EXPOSURE = fields("image_id int, mjd_min double, mjd_max double, n_sources long, band string, exptime double, order_count long, n_objects long, n_finished long, flux_min double, flux_max double, area_sum double, ellipticity_max double, first_quality string, last_order long")
SKY_OBJECT = fields("object_id long, first_source_id long, datapoints int, active boolean, mean_ra_deg double, mean_dec_deg double, x double, y double, z double, strip int")
LIGHTCURVE = fields("object_id long, source_id long, image_id int, mjd double, flux double, flux_err double, sep_arcsec double, topology string")
QUERY_LOG = fields("run_id string, image_id int, step string, query string, seconds double, rows_out long, rows_scanned long, n_database long")


def conform(df: DataFrame, schema: StructType) -> DataFrame:
    """df with exactly the schema's columns and types; a missing column is an error."""
    missing = [f.name for f in schema if f.name not in df.columns]
    if missing:
        raise ValueError(f"missing columns: {missing}")
    return df.select(*[df[f.name].cast(f.dataType) for f in schema])
