"""Spark-native engine for plot-faithful row samples.

Functions of this package that run on executors are shipped by value, so executors need only
PySpark, numpy and pyarrow, not this package.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
