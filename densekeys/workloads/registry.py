"""All queries of the library by name."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from densekeys.plans.build import build_two_level
from densekeys.plans.evaluate import lookup
from densekeys.plans.params import Params
from densekeys.workloads import apps, methods, relational, streams, tables, variants

PARTS = (methods, tables, apps, relational, streams, variants)
QUERIES = {name: query for part in PARTS for name, query in part.QUERIES.items()}
ORACLES = {name: sql for part in PARTS for name, sql in part.ORACLES.items()}


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Every URL with its dense id, by the proved construction."""
    urls = methods.table(spark, sf_dir, "pages").select("url")
    return lookup(urls, build_two_level(urls, "url", Params(hash="linear"))).select("url", "id")
