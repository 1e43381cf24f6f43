"""Graph summaries on Spark: detect communities in an edge stream, merge them, lay out and draw the result."""

import sys

from pyspark import cloudpickle

__version__ = "0.1.0"

# Python workers get our functions with the task, so executors need no copy of this package.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
