"""Tree-collection compression and large-scale text operators on PySpark."""

from __future__ import annotations

import sys

from pyspark import cloudpickle

# functions sent to executors carry their code with them, so nothing has to be installed there
cloudpickle.register_pickle_by_value(sys.modules[__name__])
