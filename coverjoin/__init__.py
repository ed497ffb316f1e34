"""Natural joins over many relations whose work stays within the fractional cover bound of the output."""

import sys

from pyspark import cloudpickle

# Functions that run on executors are sent with their code, so that a cluster needs no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
