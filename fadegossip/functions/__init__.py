"""SQL functions, table functions and pandas functions of the engine."""

from fadegossip.functions.sql import register
from fadegossip.functions.udfs import HashRows, PlanParameters, fold_udf, zipf_rank

__all__ = ["HashRows", "PlanParameters", "fold_udf", "register", "zipf_rank"]
