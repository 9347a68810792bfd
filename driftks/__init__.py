"""Distribution-shift testing on very large tables with Spark's quantile summaries.

Functions that run in Python workers are pickled by value, so the workers need no copy of the package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
