"""All queries of the library: importing the modules registers them."""

from reclink.queries import compare, linkage, selection, surface  # noqa: F401
from reclink.queries._registry import ORACLES, QUERIES  # noqa: F401
