"""The operators on relations, under one name."""

from ..acyclic import acyclic_boolean, acyclic_evaluate, full_reduction, reduce_bags
from ..instance import natural_join, project, select_eq, semijoin
from ..partition import equal_degree_parts, heavy_light
from ..statistics import degree_at, degrees, max_degree

__all__ = ["acyclic_boolean", "acyclic_evaluate", "degree_at", "degrees", "equal_degree_parts", "full_reduction", "heavy_light", "max_degree", "natural_join", "project", "reduce_bags", "select_eq", "semijoin"]
