"""All registered queries of the volume engine."""

from . import more_queries as _more  # registers its queries too
from . import operator_queries as _operators
from . import queries as _queries
from . import view_queries as _views

assert _more and _operators and _views

QUERIES = dict(_queries.QUERIES)
ORACLES = dict(_queries.ORACLES)
