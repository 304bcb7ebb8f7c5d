"""Given tables, edge lists and route files, read and written with declared schemas."""

from .edge_list import register_edge_list
from .tables import table, tables
from .writers import write_bucketed, write_by_cell, write_geojson_lines

__all__ = ["register_edge_list", "table", "tables", "write_bucketed", "write_by_cell", "write_geojson_lines"]
