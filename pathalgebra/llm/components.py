"""Groups of linked rows: the engine's undirected components under the name that the operators use."""

from __future__ import annotations

from pathalgebra.operators.contraction import connected as components

__all__ = ["components"]
