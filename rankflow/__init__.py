"""rankflow: linear-algebra views on Spark, kept fresh by low-rank changes."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to Python workers by value, so executors need no copy of the repository.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
