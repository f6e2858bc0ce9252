"""Operators for preparing language-model training data.

Nothing outside this subpackage imports it. ``queries.py`` registers one query
for each operator.
"""

import sys

from pyspark import cloudpickle

# functions sent to executors carry their code: no executor needs this package installed
cloudpickle.register_pickle_by_value(sys.modules[__name__])
