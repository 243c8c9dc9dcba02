"""Every registered query: importing the modules registers them."""

from ..registry import ORACLES, QUERIES
from . import aggregates, costs, media, more, rasters, relational, streams, studies, surround

__all__ = ["ORACLES", "QUERIES", "aggregates", "costs", "media", "more", "rasters", "relational", "streams", "studies", "surround"]
