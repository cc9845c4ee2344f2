"""A Spark-native engine that imputes missing values in multi-attribute data streams."""

import sys

from pyspark import cloudpickle

# Executors need not have this package on their path: functions sent to them carry their code.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
