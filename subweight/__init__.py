"""Bottom-k sketches of weighted tables and estimates of subpopulation weights, on Spark."""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
