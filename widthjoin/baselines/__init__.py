"""The methods the guided evaluator is compared with."""

from .boolean_product import boolean_product, min_plus_cycle
from .dual_rules import disjunctive_rule, dual_rules_evaluate
from .pairwise import pairwise_evaluate
from .single_tree import single_tree_evaluate
from .uniformize import uniformity_gap, uniformize_evaluate

__all__ = ["boolean_product", "disjunctive_rule", "dual_rules_evaluate", "min_plus_cycle", "pairwise_evaluate", "single_tree_evaluate", "uniformity_gap", "uniformize_evaluate"]
