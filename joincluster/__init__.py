"""joincluster: cluster the rows of a multi-table feature query without building its joined matrix."""

import sys

from pyspark import cloudpickle

# Tasks get this package's functions by value, so executors need no copy of it on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
