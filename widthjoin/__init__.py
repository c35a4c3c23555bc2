"""Width-guided evaluation of conjunctive queries on Spark DataFrames."""

from .functions.tables import sql

__all__ = ["sql"]
