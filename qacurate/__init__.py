"""A Spark-native engine that curates question-answer data and measures it."""

import sys

from pyspark import cloudpickle

# Functions sent to executors carry their code, so a cluster needs no installed copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
