"""Connected components, as the graphs have them."""

from levelmine.graph.components import components

__all__ = ["components"]
