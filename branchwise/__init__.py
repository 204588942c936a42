"""Labelled subgraph matching on Spark that learns from failed branches.

Functions that run in Python workers are pickled by value, so executors need not have this
package on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
