"""Names, keys and constants of the data model."""

from __future__ import annotations

from dataclasses import dataclass

DAY = 86_400_000_000
HOUR = 3_600_000_000

#: Event type to feature group: dense views and clicks, sparse explicit actions, the rest.
GROUPS = {"view": "dense", "click": "dense", "purchase": "sparse", "signup": "sparse", "error": "ops"}
EVENT_COLUMNS = ("us", "event_id", "event_type", "value", "item_id")
STRIPE_KEY = ("user_id", "feature_group", "first_us")
STRIPE_INDEX = ("user_id", "feature_group", "stripe_no", "first_us", "last_us", "n_events", "events_before")
ONE_GROUP = "all"


@dataclass(frozen=True)
class PointerSpec:
    """How a request's window is cut: at the last multiple of cadence before t - lag, lookback_days back."""

    cadence: int = DAY
    lag: int = 0
    lookback_days: int = 30
    per_group: bool = False
    digest: str | None = "additive"


@dataclass(frozen=True)
class LayoutSpec:
    """Stripes of stripe_len events (mode count) or of a fixed span of time (mode time)."""

    stripe_len: int = 8
    mode: str = "count"
    span: int = DAY
    per_group: bool = False
    buckets: int = 8


@dataclass(frozen=True)
class TenantSpec:
    """A model's demand: how many latest events, of which groups, with which traits, by how many jobs."""

    name: str
    seq_len: int
    jobs: int = 1
    groups: tuple[str, ...] | None = None
    traits: tuple[str, ...] = EVENT_COLUMNS


TENANTS = (TenantSpec("A", 64, 2), TenantSpec("B", 16, 20), TenantSpec("C", 4, 20))
