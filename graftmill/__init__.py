"""graftmill: graph-grounded instruction data for Spark.

Sub-packages
------------
sources     typed table readers and file sinks
functions   column-level building blocks (text, hashing, vectors, scores)
operators   relational operators over DataFrames (segmentation, graph, loop, theory, metrics)
plans       plan inspection
streaming   incremental upkeep of the graph
workloads   the experiments, one function per registered query
llm         training-data operators; nothing else in the package imports it
"""

__version__ = "0.1.0"

import sys as _sys

from pyspark import cloudpickle as _cloudpickle

# Functions for Python workers travel by value: executors need no copy of the package.
_cloudpickle.register_pickle_by_value(_sys.modules[__name__])
