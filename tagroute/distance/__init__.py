"""Shortest distances: arrays in a task for networks of a checked size, DataFrame rounds over cells for larger ones."""

from .arrays import Csr, sssp
from .wide import same_cell_true, sssp_wide

__all__ = ["Csr", "same_cell_true", "sssp", "sssp_wide"]
