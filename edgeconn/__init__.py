"""Edge connectivity (global minimum cut) of very large simple graphs on Spark."""

import sys

from pyspark import cloudpickle

# Functions that run on executors travel with their code, so that workers do
# not need this package on their own import path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
