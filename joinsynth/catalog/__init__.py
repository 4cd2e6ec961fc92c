"""Registered queries of the library and their SQL, by the identifiers of the blueprint."""

from __future__ import annotations

from . import analysis, core, noise_and_release, seeded_releases, user_operators
from .registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "analysis", "core", "noise_and_release", "seeded_releases", "user_operators"]
