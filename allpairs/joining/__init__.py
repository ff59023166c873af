"""Ways to give every raw row the totals of its entity."""

from .lookup import LookupTableTooLarge, attach_lookup, lookup_build
from .online import attach_online
from .sharding import attach_sharding, sharded_totals

__all__ = ["LookupTableTooLarge", "attach_lookup", "attach_online", "attach_sharding", "lookup_build", "sharded_totals"]
