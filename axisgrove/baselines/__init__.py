"""The designs that the tree is compared with. All answer the same queries with the same rows."""

from axisgrove.baselines.brute import brute_count, brute_knn, brute_range
from axisgrove.baselines.full_rebuild import FullRebuildTree
from axisgrove.baselines.log_forest import LogForest
from axisgrove.baselines.sequential import SequentialTree
from axisgrove.baselines.zorder import ZOrderTree

__all__ = ["FullRebuildTree", "LogForest", "SequentialTree", "ZOrderTree", "brute_count", "brute_knn", "brute_range"]
