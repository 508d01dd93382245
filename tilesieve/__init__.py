"""Membership of texts in very large corpora by tiled Bloom filters, re-expressed for Spark."""

import sys

from pyspark import cloudpickle

# executors get the functions that tasks run by value, so they need no copy of this package
cloudpickle.register_pickle_by_value(sys.modules[__name__])
