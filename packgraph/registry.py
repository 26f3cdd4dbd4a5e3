"""Merges the queries and SQL of all modules; a name may occur once."""

from __future__ import annotations

from .adjacency import arrange, bisect, permute
from .algos import traverse
from .core import compressed
from .exp import adjacency as exp_adjacency
from .exp import library
from .graphs import generate
from .functions import scalars, sql_surface
from .measure import bounds, comm
from .operators import relational
from .sources import datasource, files
from .streaming import events
from .fine import relabel, sizes
from .offsets import access as offset_access

MODULES = (sizes, relabel, permute, offset_access, compressed, traverse, arrange, bisect, bounds, comm, generate, relational, scalars, sql_surface, files, datasource, events, exp_adjacency, library)
QUERIES: dict = {}
ORACLES: dict[str, str] = {}


def _merge() -> None:
    for m in MODULES:
        for name, f in m.QUERIES.items():
            if name in QUERIES:
                raise ValueError(f"two queries are named {name}")
            QUERIES[name] = f
        ORACLES.update(m.ORACLES)


_merge()
