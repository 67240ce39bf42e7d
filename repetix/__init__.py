"""Compressibility sketches over distinct substrings, for Spark.

Kernels that run on executors are pickled by value, so a session works with the
package whether or not the executors have the repository on their path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
