"""All workload queries and their SQL."""

from . import corpus, digest, surround  # noqa: F401
from .base import QUERIES, SQL  # noqa: F401
