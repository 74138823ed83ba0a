"""Training-data operators: one module for each, joined by ``queries`` and used by ``corpus_pipeline``."""

import sys

from pyspark import cloudpickle

# Functions of this package travel to executors by value: a session that was started without the repository on
# the workers' path runs them all the same.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
