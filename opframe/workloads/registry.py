"""All registered workloads with their oracles."""

from __future__ import annotations

from . import acme, crossing, events, structure, surface, todo, versions

MODULES = (acme, todo, events, structure, surface, versions, crossing)
QUERIES = {k: v for m in MODULES for k, v in m.QUERIES.items()}
ORACLES = {k: v for m in MODULES for k, v in m.ORACLES.items()}
