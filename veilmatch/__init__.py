"""Record linkage on Spark, in the clear and on secret shares.

Functions that run inside Arrow tasks are shipped by value, so executors need
no copy of this package on their own import path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
