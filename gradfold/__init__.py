"""gradfold: incremental-gradient analytics as order-aware folds on Spark."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the executors inside the closures that use
# them, so a cluster needs no installed copy of it.
cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
