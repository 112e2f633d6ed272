"""The named queries. Importing this package registers them."""

from . import core, relational, surface, tasks  # noqa: F401
from ..registry import QUERIES, SQL  # noqa: F401
