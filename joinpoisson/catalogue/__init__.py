"""The queries of the engine, each with its SQL where SQL can say it."""

from joinpoisson.catalogue import explicit, relational, sampling, streams, udfs
from joinpoisson.catalogue.registry import ORACLES, QUERIES

__all__ = ["ORACLES", "QUERIES", "explicit", "relational", "sampling", "streams", "udfs"]
