"""Training-data operators. Nothing else in the package imports this subpackage."""

import sys

from pyspark import cloudpickle

# Workers get the operators' code with the plan, so a cluster needs no install step.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
