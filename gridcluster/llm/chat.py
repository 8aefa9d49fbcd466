"""Chat formatting: collapse of cumulative conversation snapshots, then rendering. DataFrame functions only.

Texts are read twice, once for digests and once, of the conversations that stay, for rendering; what is
ordered, numbered, hashed over and joined in between are digests of 16 bytes a turn.
"""

from __future__ import annotations

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import materialise

#: Turns that are rendered together; longer conversations go on in further segments.
SEGMENT = 1024
#: Rows of a digest table (up to 64 bytes each) that may be broadcast; a larger one is joined by exchange.
BROADCAST_ROWS = 150_000


def _digest(seed: int, *cols: str) -> Column:
    parts = [F.lit(seed)]
    for c in cols:
        parts += [F.col(c).isNull(), F.col(c)]
    return F.xxhash64(*parts)


def _turns(turns: DataFrame, conv_col: str, turn_col: str, role_col: str, text_col: str) -> DataFrame:
    """c (the conversation id in a struct: a null id is a value like others), turn, role, text, d1, d2."""
    rows = turns.select(F.struct(F.col(conv_col).alias("conv")).alias("c"), F.col(turn_col).cast("long").alias("turn"), F.col(role_col).alias("role"), F.col(text_col).alias("text"))
    return rows.withColumn("d1", _digest(17, "role", "text")).withColumn("d2", _digest(90_001, "role", "text"))


def _small(df: DataFrame) -> DataFrame | None:
    """df marked for broadcast if its rows are few, df itself if not, None if it has none."""
    n = df.limit(BROADCAST_ROWS + 1).count()
    return None if not n else F.broadcast(df) if n <= BROADCAST_ROWS else df


def ordered_turns(rows: DataFrame) -> DataFrame:
    """Distinct turns in the order of conversation, number, role and text (null first), as digests: c, turn, d1, d2, ord, part.

    A global sort by ranges, so one long conversation is spread over tasks like many short ones. Text
    is a sort key only where a conversation has one number and role with several texts.
    """
    named = rows.withColumn("k1", _digest(3, "c", "turn", "role")).withColumn("k2", _digest(5, "c", "turn", "role"))
    who = F.struct("d1", "d2")
    tied = named.groupBy("k1", "k2").agg(F.min(who).alias("a"), F.max(who).alias("z")).where("a < z").select("k1", "k2")
    tied = _small(materialise(rows.sparkSession, tied, "tied-turns"))
    by_text = F.lit(None).cast("string")
    if tied is not None:
        named, by_text = named.join(tied.withColumn("tie", F.lit(True)), ["k1", "k2"], "left"), F.when(F.col("tie"), F.col("text"))
    order = ["c", "turn", "role", "by_text"]
    distinct = named.select("c", "turn", "role", by_text.alias("by_text"), "d1", "d2").distinct()
    placed = distinct.repartitionByRange(*order).sortWithinPartitions(*order).select("c", "turn", "d1", "d2", F.monotonically_increasing_id().alias("ord"))
    return placed.withColumn("part", F.shiftright("ord", 33))


def numbered_turns(rows: DataFrame) -> DataFrame:
    """Positions and rolling prefix digests of distinct turns: c, turn, d1, d2, pos, n (turns of the conversation), p1, p2.

    A turn's digest takes its position, role and text; a prefix's digest is the exclusive-or of its
    turns' digests, twice 64 bits. Counts and digests are built in two levels: within the part of a
    conversation that lies in one range of the sort, and over those parts.
    """
    spark = rows.sparkSession
    turns = materialise(spark, ordered_turns(rows), "ordered-turns")
    own = ["c", "part"]
    parts = Window.partitionBy("c").orderBy("part")
    before, every = parts.rowsBetween(Window.unboundedPreceding, -1), Window.partitionBy("c")
    runs = turns.groupBy(*own).agg(F.count(F.lit(1)).alias("k"), F.min("ord").alias("least"))
    runs = runs.select(*own, (F.coalesce(F.sum("k").over(before), F.lit(0)) - F.col("least") + 1).alias("shift"), F.sum("k").over(every).alias("n"))
    hashed = turns.join(runs, own).withColumn("pos", F.col("ord") + F.col("shift"))
    hashed = hashed.withColumn("h1", F.xxhash64(F.lit(17), "pos", "d1")).withColumn("h2", F.xxhash64(F.lit(90_001), "pos", "d2"))
    totals = hashed.groupBy(*own).agg(F.bit_xor("h1").alias("t1"), F.bit_xor("h2").alias("t2"))
    carried = totals.select(*own, *(F.coalesce(F.bit_xor(f"t{i}").over(before), F.lit(0).cast("long")).alias(f"b{i}") for i in (1, 2)))
    upto = Window.partitionBy(*own).orderBy("ord").rowsBetween(Window.unboundedPreceding, 0)
    chained = hashed.withColumn("x1", F.bit_xor("h1").over(upto)).withColumn("x2", F.bit_xor("h2").over(upto)).join(carried, own)
    return materialise(spark, chained.select("c", "turn", "d1", "d2", "pos", "n", F.expr("x1 ^ b1").alias("p1"), F.expr("x2 ^ b2").alias("p2")), "numbered-turns")


def maximal_conversations(numbered: DataFrame) -> DataFrame:
    """Conversations that no other one continues: c, n_turns, n_equal.

    Of conversations with equal turns the smallest id stays (null first); n_equal counts them. The
    others are collapsed before the anti-join, so its two sides hold each digest once.
    """
    key = [F.col("pos").alias("n_turns"), "p1", "p2"]
    full = numbered.where("pos = n").groupBy(*key).agg(F.min("c").alias("c"), F.count(F.lit(1)).alias("n_equal"))
    prefixes = numbered.where("pos < n").select(*key).distinct()
    return full.join(prefixes, ["n_turns", "p1", "p2"], "left_anti").select("c", "n_turns", "n_equal")


def render_conversations(turns: DataFrame, conv_col: str = "conv_id", turn_col: str = "turn", role_col: str = "role", text_col: str = "text", segment: int = SEGMENT) -> DataFrame:
    """Maximal conversations as text: conv_id, segment, n_turns, n_equal, text.

    A turn is `<|role|>`, a line break, its text and `<|end|>` with a line break; a null role is
    `unknown`, a null text is empty. Turns are ordered by number (null first), then role and text;
    rows that repeat a turn in full count once. Rows without a conversation id form one conversation.
    A conversation of more than `segment` turns is rendered in several rows. Other columns, of whatever
    name, are not looked at; an empty table gives no row.
    """
    rows = _turns(turns, conv_col, turn_col, role_col, text_col)
    numbered = numbered_turns(rows)
    kept = maximal_conversations(numbered)
    wanted = numbered.select("c", F.col("turn").alias("t"), "d1", "d2", "pos").join(kept, "c")
    wanted = materialise(rows.sparkSession, wanted.withColumn("segment", F.expr(f"(pos - 1) div {int(segment)}")), "kept-turns")
    small = _small(wanted)
    found = rows.join(wanted if small is None else small, (rows["c"] == wanted["c"]) & rows["turn"].eqNullSafe(wanted["t"]) & (rows["d1"] == wanted["d1"]) & (rows["d2"] == wanted["d2"]))
    line = F.concat(F.lit("<|"), F.coalesce("role", F.lit("unknown")), F.lit("|>\n"), F.coalesce("text", F.lit("")), F.lit("<|end|>\n"))
    found = found.select(rows["c"]["conv"].alias("conv"), "segment", "n_turns", "n_equal", F.struct("pos", line.alias("line")).alias("at"))
    # a set: rows that repeat a turn give the same element
    grouped = found.groupBy("conv", "segment").agg(F.first("n_turns").alias("n_turns"), F.first("n_equal").alias("n_equal"), F.sort_array(F.collect_set("at")).alias("lines"))
    return grouped.select(F.col("conv").alias(conv_col), "segment", "n_turns", "n_equal", F.array_join(F.col("lines.line"), "").alias("text"))


def oracle(table: str = "conversations") -> str:
    """The same rows in DuckDB SQL, by comparing the turns themselves."""
    return f"""
WITH t AS (SELECT DISTINCT conv_id, turn, role, text FROM {table}),
n AS (SELECT *, row_number() OVER (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role NULLS FIRST, text NULLS FIRST) AS pos FROM t),
c AS (SELECT conv_id, count(*) AS n_turns, list({{'r': role, 't': text}} ORDER BY pos) AS turns,
      string_agg('<|' || coalesce(role, 'unknown') || '|>' || chr(10) || coalesce(text, '') || '<|end|>' || chr(10), '' ORDER BY pos) AS text FROM n GROUP BY conv_id),
p AS (SELECT DISTINCT list_slice(turns, 1, k) AS turns FROM (SELECT turns, unnest(range(1, n_turns)) AS k FROM c)),
e AS (SELECT turns, min(conv_id) AS conv_id, count(*) AS n_equal FROM c GROUP BY turns)
SELECT c.conv_id, CAST(0 AS BIGINT) AS segment, c.n_turns, e.n_equal, c.text FROM e JOIN c ON c.conv_id = e.conv_id
WHERE NOT EXISTS (SELECT 1 FROM p WHERE p.turns = e.turns)"""
