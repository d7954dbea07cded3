"""Role-aware top-k vector search on Spark, planned over exclusive access blocks."""

import sys

from pyspark import cloudpickle

# Python workers of a cluster may lack this package on their path: functions travel with their code.
cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
