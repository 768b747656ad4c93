"""cellgraph: graph analytics on Spark whose unit of work is a connected cell of a part."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the executors by value, so it need not be installed there.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
