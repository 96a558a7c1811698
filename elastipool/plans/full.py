"""The whole catalogue: importing the modules fills it."""

from elastipool.plans import dashboards, more, streams, variants  # noqa: F401
from elastipool.plans.catalog import CATALOG

__all__ = ["CATALOG"]
