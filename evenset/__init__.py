"""evenset: label-free, balanced curation of very large embedded data sets on Spark."""

import sys

from pyspark import cloudpickle

# Worker functions travel by value, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
