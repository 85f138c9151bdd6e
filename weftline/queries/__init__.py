"""Registered queries and their SQL."""

from . import checks, methods, surface  # noqa: F401
from .base import ORACLES, QUERIES  # noqa: F401
