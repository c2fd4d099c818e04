"""All queries of the library and their SQL."""

from __future__ import annotations

from .queries import models, sketches, streams, surface

QUERIES = sketches.QUERIES | models.QUERIES | surface.QUERIES | streams.QUERIES
ORACLE = sketches.ORACLE | models.ORACLE | surface.ORACLE | streams.ORACLE
