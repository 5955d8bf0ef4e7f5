"""Query modules of the library itself."""

from evigraph.queries import baselines, method, relational, streams

MODULES = [method, baselines, relational, streams]
