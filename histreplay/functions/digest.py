"""Digests of event sequences."""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F


def event_text(us: Column, event_id: Column) -> Column:
    return F.concat_ws(":", us.cast("string"), event_id.cast("string"))


def ordered(us: Column, event_id: Column) -> Column:
    """Order-sensitive digest of parallel arrays: MD5 over us:event_id, comma-joined; of nothing for empty arrays."""
    return F.md5(F.concat_ws(",", F.zip_with(us, event_id, event_text)))


def event_hash(us: Column, event_id: Column) -> Column:
    """32 bits of an event; sums of them make the additive digest."""
    return F.conv(F.substring(F.md5(event_text(us, event_id)), 1, 8), 16, 10).cast("long")


def additive(total: Column) -> Column:
    """A sum of event hashes modulo 2^32; the digest of a range is the difference of two prefix sums, modulo 2^32."""
    return F.pmod(total, F.lit(1 << 32))
