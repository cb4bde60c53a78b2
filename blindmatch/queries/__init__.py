"""All queries of the linkage engine and its operators, with their SQL."""

from blindmatch.operators import clustering
from blindmatch.queries import experiments, linkage, prep, relational, streams, workloads  # noqa: F401
from blindmatch.queries.registry import ORACLES, QUERIES


def flagship(spark, sf_dir):
    """Early mapping of three parties with two-name blocks: the clusters of two or more records."""
    found = clustering.cluster_early(workloads.masked(workloads.parties(spark, sf_dir, 3)))
    return clustering.matches(found, 2)


__all__ = ["ORACLES", "QUERIES", "flagship"]
