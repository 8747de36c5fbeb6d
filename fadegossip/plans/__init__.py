"""Lineage cuts and checks of physical plans."""

from fadegossip.plans.checks import operators_of, pushed_filters, read_columns, shuffles
from fadegossip.plans.lineage import checked, cut, ensure_checkpoint_dir

__all__ = ["checked", "cut", "ensure_checkpoint_dir", "operators_of", "pushed_filters", "read_columns", "shuffles"]
