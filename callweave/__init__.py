"""callweave: stateless-function analytics on Spark.

Functions shipped to executors are pickled by value, so a cluster needs no
installed copy of this package and a call always runs the submitted code.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
