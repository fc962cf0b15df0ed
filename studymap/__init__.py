"""studymap: assigns multi-part records ("studies") to the classes of a local catalogue, on PySpark.

Python functions that reach executors are pickled by value, so a cluster needs no copy of the package on its workers.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
