"""Model-based relational archives on Spark: learned dependency networks, arithmetic-coded rows, and the operators around them."""

import sys

from pyspark import cloudpickle

# Functions of this package travel by value, so executors need no copy of the repository on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
