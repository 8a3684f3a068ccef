"""Training-data operators: dedup, quality, private data, fingerprints, token output and packing.

Nothing outside this package imports it.  Kernels are shipped to the executors by value, so they
run on a session that was started without this repository on its workers' path.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
