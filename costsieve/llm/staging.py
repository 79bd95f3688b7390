"""Staged tables and the shipping of the package, as the rest of the library has them."""

from ..sources.shared import FALLBACK_DIR, Staging, shared_dir, ship

__all__ = ["FALLBACK_DIR", "Staging", "shared_dir", "ship"]
