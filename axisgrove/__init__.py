"""A Spark-native batch-dynamic kd-tree engine."""

import sys

from pyspark import cloudpickle

# Executors need not have the package installed: functions sent to them carry its code along.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
