"""Pattern queries over language models as Spark relations."""

import sys

from pyspark import cloudpickle

# Functions shipped to executors travel by value, so workers need no copy of the package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
