"""SQL of the queries, for another engine on the same tables."""

from pipeflow import surface, workloads  # noqa: F401
from pipeflow.registry import ORACLES  # noqa: F401
