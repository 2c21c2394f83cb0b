"""Training-data operators. Nothing else in the package imports this subpackage.

Functions of this subpackage travel to the executors by value, so that a session which has the
repository on the driver's path only can run them.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
