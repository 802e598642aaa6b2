"""Training-data operators. Nothing outside this subpackage imports it, so it can be removed whole."""

import sys

from pyspark import cloudpickle

# Worker functions travel by value: executors then need no copy of this package on their path.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
