"""All registered queries."""

from . import q_chains, q_fits, q_model, q_prep, q_private, q_replay, q_stream, q_surface, q_terms  # noqa: F401
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES"]
