"""Approximate ranks and quantiles over very large data, on Spark."""

import sys

from pyspark import cloudpickle

# Functions that run on executors travel with the job: no copy of the package is needed there.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
