"""Builds of the immutable tier: full rebuild, advance by one day, publishing, and what a build may change."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, DataFrameWriter, SparkSession
from pyspark.sql import functions as F

from histreplay.functions.digest import event_hash
from histreplay.operators import stripes, tier
from histreplay.schema import DAY, EVENT_COLUMNS, STRIPE_INDEX, LayoutSpec

#: A dimension or deletion list with at most this many rows is broadcast.
BROADCAST_ROWS = 1_000_000


@dataclass(frozen=True)
class SideInfo:
    """A column that a build attaches to events by item: table has item_id and the column."""

    table: DataFrame = field(compare=False)
    column: str = ""


def _small(df: DataFrame) -> DataFrame:
    return F.broadcast(df) if df.limit(BROADCAST_ROWS + 1).count() <= BROADCAST_ROWS else df


def scrub(hist: DataFrame, items: DataFrame | None = None, users: DataFrame | None = None) -> DataFrame:
    """Without the events of deleted items (item_id) and accounts (user_id)."""
    if items is not None:
        hist = hist.join(_small(items.select("item_id").distinct()), "item_id", "left_anti")
    if users is not None:
        hist = hist.join(_small(users.select("user_id").distinct()), "user_id", "left_anti")
    return hist


def window(hist: DataFrame, as_of: int, lookback_days: int) -> DataFrame:
    return hist.filter((F.col("us") < as_of) & (F.col("us") >= as_of - lookback_days * DAY))


def rebuild(source: DataFrame, as_of: int, lookback_days: int = 30, layout: LayoutSpec = LayoutSpec(), items: DataFrame | None = None, users: DataFrame | None = None, add: tuple[SideInfo, ...] = (), drop: tuple[str, ...] = ()) -> DataFrame:
    """The whole lookback window before as_of as stripes: deletions applied, side columns added, unused ones dropped."""
    hist = scrub(window(source, as_of, lookback_days), items, users)
    for side in add:
        own = side.table.select("item_id", side.column).dropDuplicates(["item_id"])
        hist = hist.join(_small(own), "item_id", "left")
    traits = tuple(t for t in (*EVENT_COLUMNS, *(s.column for s in add)) if t not in drop)
    return stripes.build(hist, layout, traits)


def advance(previous: DataFrame, new_day: DataFrame, as_of: int, lookback_days: int = 30, layout: LayoutSpec = LayoutSpec()) -> DataFrame:
    """The next generation from the last one and one new day: equal to a rebuild, without reading the older events again.

    Stripes are cut anew, since those that leave the window move the ranks; both sides are shuffled by user and group.
    """
    old = stripes.explode(previous)
    new = new_day.select(*old.columns) if layout.per_group else new_day.withColumn("feature_group", F.lit("all")).select(*old.columns)
    return stripes.build(window(old.unionByName(new), as_of, lookback_days), layout)


def content_digest(generation: DataFrame) -> DataFrame:
    """(events, digest): equal for equal content, however it is cut or stored."""
    rows = stripes.explode(generation, ("us", "event_id"))
    return rows.agg(F.count("*").alias("events"), F.sum(event_hash(F.col("us"), F.col("event_id"))).alias("digest"))


class Registry:
    """Generations as bucketed, sorted, encoded tables, and a table of what was published; readers pin a number.

    The state is in the registry table, a row for each publication or rollback, so that any driver sees it.
    """

    def __init__(self, spark: SparkSession, name: str = "history", layout: LayoutSpec = LayoutSpec(), root: str | None = None) -> None:
        self.spark, self.name, self.layout, self.root = spark, name, layout, root

    def table(self, gen: int) -> str:
        return f"{self.name}_g{gen}"

    def _save(self, writer: DataFrameWriter, table: str) -> None:
        (writer if self.root is None else writer.option("path", f"{self.root}/{table}")).saveAsTable(table)

    def write(self, generation: DataFrame, gen: int, codecs: dict[str, str] | None = None) -> str:
        """One shuffle into `buckets` buckets by user, sorted by the stripe key; single level, never appended to.

        codecs: of each trait, plain if not given. How to read them is kept as a property of the table.
        """
        n = self.layout.buckets
        codecs = codecs or {t: "plain" for t in generation.columns if t not in STRIPE_INDEX}
        ready = tier.encode(generation, codecs).repartition(n, "user_id").sortWithinPartitions("user_id", "feature_group", "first_us")
        self._save(ready.write.mode("overwrite").bucketBy(n, "user_id").sortBy("user_id", "feature_group", "first_us"), self.table(gen))
        told = tier.describe(codecs, generation).replace("'", "\\'")
        self.spark.sql(f"ALTER TABLE {self.table(gen)} SET TBLPROPERTIES ('traits' = '{told}')")
        return self.table(gen)

    def _log(self) -> list:
        if not self.spark.catalog.tableExists(f"{self.name}_registry"):
            return []
        self.spark.catalog.refreshTable(f"{self.name}_registry")
        return self.spark.table(f"{self.name}_registry").orderBy("seq").collect()

    @property
    def published(self) -> list[int]:
        """Publications in force, the last one being read."""
        out: list[int] = []
        for r in self._log():
            if r["action"] == "publish":
                out.append(r["gen"])
            else:
                out = [g for g in out if g != r["gen"]] if r["action"] == "vacuum" else out[:-1]
        return out

    def _note(self, action: str, gen: int) -> None:
        row = self.spark.createDataFrame([(len(self._log()), action, gen)], "seq long, action string, gen int")
        self._save(row.coalesce(1).write.mode("append"), f"{self.name}_registry")

    def publish(self, gen: int) -> None:
        """The switch, one appended row: new readers see gen, those that pinned another go on with it."""
        self._note("publish", gen)
        self.read(gen).createOrReplaceTempView(self.name)

    def rollback(self) -> int:
        """Back to the publication before; refused if there is none."""
        order = self.published
        if len(order) < 2:
            raise ValueError("no earlier publication to go back to")
        self._note("rollback", order[-1])
        self.read(order[-2]).createOrReplaceTempView(self.name)
        return order[-2]

    def read(self, gen: int | None = None, traits: tuple[str, ...] | None = None) -> DataFrame:
        """Stripes of the pinned generation, or of the published one, with the wanted traits (all if None)."""
        name = self.table(self.published[-1] if gen is None else gen)
        told = self.spark.sql(f"SHOW TBLPROPERTIES {name}('traits')").first()["value"]
        return tier.opened(self.spark.table(name), told, traits)

    def vacuum(self, keep: int = 2) -> list[int]:
        """Drops all but the last `keep` published generations; gives those dropped."""
        order = list(dict.fromkeys(self.published))
        gone = order[: max(0, len(order) - keep)]
        for gen in gone:
            self.spark.sql(f"DROP TABLE IF EXISTS {self.table(gen)}")
            self._note("vacuum", gen)
        return gone
