"""Road networks and POI layers from the given tables."""

from .build import arcs, lattice, lattice_from_orders, proximity, trade
from .place import edge_pois, explode_tags, personal_ratings, pois_customer, pois_documents, pois_part, pois_supplier, snap_nearest, split_edges
from .scale import fit_scale

__all__ = ["arcs", "edge_pois", "explode_tags", "fit_scale", "lattice", "lattice_from_orders", "personal_ratings", "pois_customer", "pois_documents", "pois_part", "pois_supplier", "proximity", "snap_nearest", "split_edges", "trade"]
