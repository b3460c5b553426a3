"""Second-order space-time point pattern analytics as Spark DataFrame plans."""

import sys

from pyspark import cloudpickle

# Functions that run in Python workers travel by value, so a session started
# without this package on the executors' path still works.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
