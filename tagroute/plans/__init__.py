"""How plans are cut, bounded and chosen."""

from .mode import choose_mode
from .rounds import discard, materialize

__all__ = ["choose_mode", "discard", "materialize"]
