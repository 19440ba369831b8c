"""Registered queries of the reference's own methods, by area."""

from qacurate.queries import curate, decontam, dedup, evaluate, recipes, relational, sources, streaming, textbook  # noqa: F401
from qacurate.registry import REGISTRY

__all__ = ["REGISTRY"]
