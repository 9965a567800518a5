"""minlabel: connected components of very large graphs by minimum-label mapping, on PySpark DataFrames."""

import sys

from pyspark import cloudpickle

# Executors need not have this package on their path: its functions travel with the tasks.
cloudpickle.register_pickle_by_value(sys.modules[__name__])

__version__ = "0.1.0"
