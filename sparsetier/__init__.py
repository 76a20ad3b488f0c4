"""Two-level sparse matrix products and data-preparation operators on Spark."""

import sys

from pyspark import cloudpickle

# Functions sent to executors carry their code, so that workers need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
