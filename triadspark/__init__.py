"""Triad census of large directed graphs on Spark, and operators for text corpora (subpackage llm)."""

import sys

from pyspark import cloudpickle

# Python workers get this package's functions by value: nothing has to be installed on executors.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
