"""Column functions: coins that hash content, and canonical edges."""

from .coins import COIN_RANGE, coin52, edge_hi, edge_lo, register_sql_functions

__all__ = ["COIN_RANGE", "coin52", "edge_hi", "edge_lo", "register_sql_functions"]
