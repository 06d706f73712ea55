"""Common table expressions of the DuckDB twins: brute force, with no stripe and no pointer in them."""

from __future__ import annotations

DAY, HOUR = 86_400_000_000, 3_600_000_000

#: H: canonical events. R: requests with cutoff c_us and window start lo_us. W: events of each request's window.
HIST = """H AS (
  SELECT user_id, epoch_us(ts) AS us, event_id, event_type, value, CAST(regexp_extract(props, '([0-9]+)', 1) AS INTEGER) AS item_id,
         CASE WHEN event_type IN ('view', 'click') THEN 'dense' WHEN event_type IN ('purchase', 'signup') THEN 'sparse' ELSE 'ops' END AS feature_group
  FROM events)"""


def requests(lookback: int = 30, hist: str = "H") -> str:
    return f"""R AS (
  SELECT event_id AS request_id, user_id, us AS t_us, us // {DAY} * {DAY} AS c_us, us // {DAY} * {DAY} - {lookback - 1} * {DAY} AS lo_us
  FROM {hist} WHERE event_type = 'view')"""


WINDOW = """W AS (
  SELECT r.*, h.us, h.event_id, h.event_type, h.value, h.item_id, h.feature_group,
         row_number() OVER (PARTITION BY request_id ORDER BY h.us DESC, h.event_id DESC) AS back
  FROM R r JOIN H h ON h.user_id = r.user_id AND h.us <= r.t_us AND h.us >= r.lo_us)"""
DIGEST = "md5(string_agg(us || ':' || event_id, ',' ORDER BY us, event_id))"
HASH32 = "CAST('0x' || substr(md5(us || ':' || event_id), 1, 8) AS BIGINT)"
SUMMARY = f"SELECT request_id, count(*) AS n, min(us) AS first_us, max(us) AS last_us, {DIGEST} AS digest FROM W"


def base(lookback: int = 30, key: str = "user") -> str:
    """WITH clause of H, R and W; histories by user, nation or region."""
    if key == "user":
        return f"WITH {HIST}, {requests(lookback)}, {WINDOW} "
    of = "CAST(c_nationkey AS BIGINT)" if key == "nation" else "CAST(n_regionkey AS BIGINT)"
    more = "" if key == "nation" else " JOIN nation ON n_nationkey = c_nationkey"
    keyed = f"H AS (SELECT {of} AS user_id, us, event_id, event_type, value, item_id, feature_group FROM U JOIN customer ON c_custkey = U.user_id{more})"
    return f"WITH {HIST.replace('H AS', 'U AS', 1)}, {keyed}, {requests(lookback)}, {WINDOW} "


#: Stripes of S events by rank, for counts alone.
def stripes(size: int) -> str:
    return f"N AS (SELECT *, row_number() OVER (PARTITION BY user_id ORDER BY us, event_id) - 1 AS rank FROM H), ST AS (SELECT *, rank // {size} AS stripe_no FROM N)"


#: L: for each request and length, the immutable events of the last `length`.
def tail(length: int) -> str:
    return f"(SELECT * FROM W WHERE back <= {length} AND us < c_us)"
