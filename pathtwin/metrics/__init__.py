"""Path and set distances as kernels, Arrow functions and Column expressions."""
from pathtwin.metrics.columns import distance_udf, set_distance_udf

__all__ = ["distance_udf", "set_distance_udf"]
