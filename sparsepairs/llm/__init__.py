"""Training-data operators; nothing outside this subpackage imports it."""

from . import blas  # noqa: F401
