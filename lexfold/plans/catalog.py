"""All queries by name and their DuckDB counterparts."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from ..functions import measures as M
from ..operators.fold import fold_sweep
from ..operators.kernel import Options
from . import catalog_ops, catalog_text
from .workloads import standard_shards

QUERIES = catalog_text.QUERIES | catalog_ops.QUERIES
ORACLE = catalog_text.ORACLE | catalog_ops.ORACLE


def flagship(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Both ratios of every stand-in corpus at three lengths."""
    d = fold_sweep(standard_shards(spark, sf_dir), (3, 10, 20), Options())
    return M.ratios(d, ["corpus", "l_max"]).select("corpus", "l_max", F.round("cr", 6).alias("cr"), F.round("cr_input", 6).alias("cr_input"))
