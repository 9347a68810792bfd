"""Operators for preparing training corpora, kept apart from the drift engine.

Nothing outside this package imports it. Functions that run in Python workers
are pickled by value, so the workers need no copy of the package on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
