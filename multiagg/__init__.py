"""Grouped aggregates over many-way joins, Spark-first.

The package ships its Python functions to the workers by value, so executors need
PySpark, numpy and pandas only, not this repository on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
