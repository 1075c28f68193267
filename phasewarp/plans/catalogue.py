"""All queries of the library and their SQL twins."""

from phasewarp.plans import surrounding, workloads  # noqa: F401  (they register their queries)
from phasewarp.plans.queries import QUERIES, SQL  # noqa: F401
