"""Connected components, as the library's clustering uses them."""

from ..operators.components import components

__all__ = ["components"]
