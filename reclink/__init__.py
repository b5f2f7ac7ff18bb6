"""Record linkage on incomplete data with attribute and relational signatures, built on Spark DataFrames."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to the Python workers by value: executors need
# no copy of it on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
