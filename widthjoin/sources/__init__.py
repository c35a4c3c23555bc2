"""Relations: of the given tables, of any table by expressions, and generated ones."""

from .relations import bind_atom, relation, star, star_of

__all__ = ["bind_atom", "relation", "star", "star_of"]
