"""coreclust: center-based clustering of general metric data by composable summaries on Spark."""

from .schema import ClusterSpec, CoreclustError

__all__ = ["ClusterSpec", "CoreclustError"]
