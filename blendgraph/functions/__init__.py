"""Functions for SQL: expressions where SQL has them, Arrow functions and table functions where it has not."""

from .sql_functions import PairsInWindow, WalkFrom, arrow_cosine, arrow_dot, arrow_vec_sum, register_functions

__all__ = ["PairsInWindow", "WalkFrom", "arrow_cosine", "arrow_dot", "arrow_vec_sum", "register_functions"]
