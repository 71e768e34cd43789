"""Stratified rare-event reliability estimation on Spark."""

import sys

from pyspark import cloudpickle

# Kernels travel inside their closures, so executors need no installed copy of the package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
