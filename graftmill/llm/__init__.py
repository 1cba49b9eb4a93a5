"""Training-data operators for very large corpora.

The functions that run inside Python workers are pickled by value, so that an executor needs
no copy of this package on its path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
