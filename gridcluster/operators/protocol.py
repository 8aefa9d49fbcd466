"""What crosses a party's border: messages, rounds, volume, and the check that nothing else does."""

from __future__ import annotations

from dataclasses import dataclass, field

from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

UP, DOWN = ("bounds", "codes", "anchor_codes"), ("centers", "cluster_space")
#: Columns that a hub may hold.
HUB_COLUMNS = {"row_id", "anchor_id", "row_grp", "col_grp", "code", "z"}


@dataclass(frozen=True)
class Message:
    round: int
    sender: str
    receiver: str
    kind: str
    n_rows: int
    width: int


@dataclass
class Ledger:
    messages: list[Message] = field(default_factory=list)

    def send(self, round: int, sender: str, receiver: str, kind: str, n_rows: int, width: int) -> None:
        self.messages.append(Message(round, sender, receiver, kind, int(n_rows), int(width)))

    @property
    def rounds(self) -> int:
        return len({m.round for m in self.messages})

    def volume(self, way: str | None = None) -> int:
        """Numbers sent, up to the hub, down, or both."""
        return sum(m.n_rows * m.width for m in self.messages if way is None or (m.receiver == "hub") == (way == "up"))

    def frame(self, spark: SparkSession) -> DataFrame:
        return spark.createDataFrame([tuple(vars(m).values()) for m in self.messages], "round int, sender string, receiver string, kind string, n_rows long, width int")

    def audit(self) -> None:
        """Raises if a message is of a kind that the protocol doesn't have, or a code is as wide as the data."""
        bad = [m for m in self.messages if m.kind not in UP + DOWN or (m.receiver == "hub") != (m.kind in UP)]
        if bad:
            raise AssertionError(f"messages outside the protocol: {bad[:3]}")


def hub_may_hold(df: DataFrame) -> DataFrame:
    extra = set(df.columns) - HUB_COLUMNS
    if extra:
        raise AssertionError(f"columns that don't belong at the hub: {sorted(extra)}")
    return df


def grid_ledger(row_counts: dict[int, int], widths: dict[tuple[int, int], int], anchors: int, k: int, space: int, bounds: dict[int, int] | None = None) -> Ledger:
    """One upload and one download a party; bounds: features by column party whose ranges were given for the anchors."""
    out = Ledger()
    for (i, j), w in sorted(widths.items()):
        party = f"party({i},{j})"
        if bounds:
            out.send(1, party, "hub", "bounds", bounds[j], 2)
        out.send(1, party, "hub", "codes", row_counts[i], w)
        out.send(1, party, "hub", "anchor_codes", anchors, w)
        out.send(1, "hub", party, "centers", k, space)
        out.send(1, "hub", party, "cluster_space", row_counts[i], space)
    return out


def comm_volume(rows: DataFrame, widths: dict[tuple[int, int], int], anchors: int, k: int, space: int) -> DataFrame:
    """The same volume from a table of rows, by party: row_grp, col_grp, up, down."""
    spark = rows.sparkSession
    w = spark.createDataFrame([(i, j, v) for (i, j), v in widths.items()], "row_grp int, col_grp int, w int")
    n = rows.groupBy("row_grp").agg(F.count(F.lit(1)).alias("n"))
    return n.join(F.broadcast(w), "row_grp").select("row_grp", "col_grp", ((F.col("n") + anchors) * F.col("w")).alias("up"), ((F.col("n") + k) * space).alias("down"))
