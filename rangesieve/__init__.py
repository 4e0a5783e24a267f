"""Range filters over DataFrame keys: may any key lie in [lo, hi]?  Compact, learnt from the key distribution, never a false no."""

import sys

from pyspark import cloudpickle

# kernels travel to the executors with their code, so that the package need not be installed there
cloudpickle.register_pickle_by_value(sys.modules[__name__])
