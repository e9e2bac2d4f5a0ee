"""All queries of the library."""

from pipeflow import surface, workloads  # noqa: F401
from pipeflow.registry import QUERIES  # noqa: F401
