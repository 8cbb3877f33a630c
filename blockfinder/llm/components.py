"""Connected components of links between fingerprints, as of any other edges."""

from __future__ import annotations

from ..operators.components import components

__all__ = ["components"]
