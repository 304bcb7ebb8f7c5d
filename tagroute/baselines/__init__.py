"""Methods to compare with. What is known of them is their kind; the rest is plain label setting, dominance and A*."""

from .local import METHODS

__all__ = ["METHODS"]
