"""Selectivity estimation of select-join queries on Spark by one provable sample per table."""

import sys

from pyspark import cloudpickle

# functions sent to executors carry this package's code with them, so executors need not have it installed
cloudpickle.register_pickle_by_value(sys.modules[__name__])
