"""Spark-native storage, retrieval and measurement of corpora that pair one media object with many texts."""

import sys

from pyspark import cloudpickle

# Worker functions travel with the tasks, so executors need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
