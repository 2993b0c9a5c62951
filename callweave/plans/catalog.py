"""All registered queries of the library and their SQL."""

from callweave.plans import calls, measures, patterns, relational, streams  # noqa: F401  (they enter their queries)
from callweave.plans.registry import ORACLES, QUERIES  # noqa: F401
