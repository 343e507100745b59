"""codetrees: itemsets chosen by compression, on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Executors need no copy of this package on their path: functions travel with the task.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
