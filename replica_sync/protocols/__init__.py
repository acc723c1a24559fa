"""The eight synchronisation protocols, for one or many sessions at once."""

from replica_sync.protocols.base import Replicas, SyncResult
from replica_sync.protocols.exact import bucketed, bucketed_rateless, rateless, state_driven
from replica_sync.protocols.filtered import filter_bucketed, filter_bucketed_rateless, filter_only, filter_rateless

PROTOCOLS = {f.__name__: f for f in (state_driven, bucketed, filter_only, filter_bucketed, rateless, filter_rateless, bucketed_rateless, filter_bucketed_rateless)}

__all__ = ["PROTOCOLS", "Replicas", "SyncResult", *PROTOCOLS]
