"""seqlex: cutting long symbol sequences into tokens, and measuring the choice, on Spark."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to executors by value, so a cluster needs no copy of it on its Python path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
