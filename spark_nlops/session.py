"""NL operators as DataFrame methods, and the SQL functions."""

from __future__ import annotations

from pyspark.sql import DataFrame, SparkSession

from .functions.udfs import register_snippets, register_summary
from .operators.cluster import nl_classify, nl_cluster
from .operators.filter import nl_filter
from .operators.join import nl_join
from .operators.project import nl_extract, nl_project
from .operators.rank import nl_rank
from .operators.reduce import nl_reduce
from .operators.search import nl_search, nl_similar_join
from .sources.index_source import register as register_index

METHODS = {f.__name__: f for f in (nl_filter, nl_join, nl_rank, nl_reduce, nl_project, nl_extract, nl_search, nl_similar_join, nl_cluster, nl_classify)}


def enable(spark: SparkSession) -> SparkSession:
    """Add ``df.nl_filter(...)`` and so on, and register SQL functions and the index source."""
    frame = type(spark.range(0))
    for name, method in METHODS.items():
        setattr(frame, name, method)
    register_summary(spark)
    register_snippets(spark)
    register_index(spark)
    return spark


__all__ = ["DataFrame", "enable"]
