"""Counter tables as they live inside one task."""

from .base import Header, Kernel
from .block import BlockReduce
from .factory import make_kernel
from .probing_table import ProbingTable

__all__ = ["BlockReduce", "Header", "Kernel", "ProbingTable", "make_kernel"]
