"""Operators for preparing training text, one module each.

Nothing outside this subpackage imports it.  Worker functions are pickled by
value, so executors need neither this package nor a shared file system.
"""

import sys

from pyspark import cloudpickle

cloudpickle.register_pickle_by_value(sys.modules[__name__])
