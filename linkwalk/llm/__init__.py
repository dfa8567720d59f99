"""Training-data operators: ten corpus operators that nothing else in the library imports."""

from __future__ import annotations

import sys

from pyspark import cloudpickle

# Executors get this subpackage's functions by value, so a cluster needs no copy of the repository.
cloudpickle.register_pickle_by_value(sys.modules[__name__])
