"""textmill: a PySpark-native engine that prepares and measures language-model data."""

import sys

from pyspark import cloudpickle

# Worker processes need no copy of this package on their path: its functions travel by value.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
