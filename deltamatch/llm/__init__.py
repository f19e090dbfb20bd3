"""Operators for building training data at scale; nothing else in the library imports this subpackage."""

import sys

from pyspark import cloudpickle

# Workers then need no copy of this package: its functions travel with the plan.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
