"""Which engine searches a pruned candidate space, from its measured size."""

from __future__ import annotations

import logging

from pyspark.sql import functions as F

from ..candidates import CandidateSpace

log = logging.getLogger(__name__)

#: A space of at most so many bytes is searched by executors that each hold all of it. A member and a connection are reckoned at what their Python objects take.
LOCAL_BYTES, MEMBER, CONNECTION = 64 << 20, 120, 80


def space_bytes(space: CandidateSpace) -> int:
    members = space.candidates.agg(F.coalesce(F.sum(F.size("members")), F.lit(0)).alias("n")).first()["n"]
    return MEMBER * members + CONNECTION * space.connections.count()


def choose(space: CandidateSpace, limit: int = LOCAL_BYTES) -> str:
    size = space_bytes(space)
    engine = "local" if size <= limit else "wavefront"
    log.info("candidate space of about %s bytes: %s", size, engine)
    return engine
