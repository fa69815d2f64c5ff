"""Content-only file-kind detection as Spark plans."""

import sys

from pyspark import cloudpickle

# Python stages travel to the executors by value, so a cluster needs no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
