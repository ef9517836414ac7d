"""Keyword-community search on changing two-layer graphs, written for Spark."""

import sys

from pyspark import cloudpickle

# Kernels travel with their code, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
