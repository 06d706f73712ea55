"""Session settings that the engine likes; all can be changed in a session that already runs."""

from __future__ import annotations

from pyspark.sql import SparkSession

#: Bucketed tables join on (user, stripe) without a shuffle only if the join may use a part of its keys.
RUNTIME = {
    "spark.sql.adaptive.enabled": "true",
    "spark.sql.adaptive.skewJoin.enabled": "true",
    "spark.sql.requireAllClusterKeysForCoPartition": "false",
    "spark.sql.sources.bucketing.autoBucketedScan.enabled": "true",
}


def build(name: str = "histreplay", **conf: str) -> SparkSession:
    """A session of one's own, UTC; the driver's or a cluster's session is used as it is."""
    builder = SparkSession.builder.appName(name).config("spark.sql.session.timeZone", "UTC")
    for k, v in (RUNTIME | conf).items():
        builder = builder.config(k, v)
    return builder.getOrCreate()


def tune(spark: SparkSession) -> dict[str, str | None]:
    """Sets RUNTIME in a running session; gives the former values back for restore()."""
    former = {k: spark.conf.get(k, None) for k in RUNTIME}
    for k, v in RUNTIME.items():
        spark.conf.set(k, v)
    return former


def restore(spark: SparkSession, former: dict[str, str | None]) -> None:
    for k, v in former.items():
        spark.conf.unset(k) if v is None else spark.conf.set(k, v)
