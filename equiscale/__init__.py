"""equiscale: exact equi-joins of heavily skewed relations in Spark."""

from .operators.adaptive import adaptive_join
from .operators.hotkeys import hot_keys
from .operators.selfjoin import natural_self_join
from .operators.small_large import index_broadcast_join
from .operators.staged import staged_join, staged_join_basic
from .plans.config import JoinConfig

__all__ = ["JoinConfig", "adaptive_join", "hot_keys", "index_broadcast_join", "natural_self_join", "staged_join", "staged_join_basic"]
