"""MinHash near-dedup: bottom-k sketches from one hash function, inverted lists, exact Jaccard."""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from ..session import materialise
from .common import coded, document_key, mix64, packed, slices, split_words, string_hash, texts
from .components import components

#: Retained values of a sketch; of these, so many smallest ones go into the inverted lists.
SKETCH, INDEXED = 48, 24
#: The chance that a pair at the limit shares fewer values than is asked for, by sketch or by list.
LOST = 1e-9
#: Members (and their shingles) of a chunk; longer lists and clusters are searched chunk by chunk.
CHUNK, CHUNK_SHINGLES = 128, 100_000
#: Chunks are so many times as large where members outside the largest component are compared with all others.
WIDER = 16
#: Bits of the membership filter at most, as a power of two: 4 MB.
FILTER_BITS = 25


def shared_values(k: int, percent: int) -> int:
    """How many of k values a pair at the limit shares at least, but for a chance of LOST; one at least.

    When one set holds the other (a text cut short), each of the larger one's smallest values is shared
    with a chance of the Jaccard share: the binomial case. Sets of like size share more.
    """
    j, below = percent / 100, 0.0
    for m in range(k + 1):
        below += math.comb(k, m) * j**m * (1 - j) ** (k - m)
        if below > LOST:
            return max(1, m)
    return max(1, k)


def shingle_hashes(text: pa.Array, words: int) -> tuple[np.ndarray, np.ndarray]:
    """Hashes of all word shingles of each text, and where each text's begin; a shorter text is one shingle."""
    flat, offsets = split_words(text, lower=True)
    codes, distinct = coded(flat)
    hashed = string_hash(distinct)[codes] if len(codes) else np.zeros(0, dtype=np.uint64)
    n_words = np.diff(offsets)
    size = np.where(n_words >= words, n_words - words + 1, np.minimum(n_words, 1))
    begin = np.concatenate([[0], np.cumsum(size)])
    first = np.repeat(offsets[:-1] - begin[:-1], size) + np.arange(int(begin[-1]))
    row = np.repeat(np.arange(len(n_words)), size)
    span = np.minimum(n_words, words)[row]
    h = span.astype(np.uint64) * np.uint64(0x9E3779B97F4A7C15)
    for i in range(words):
        inside = span > i
        part = hashed[np.where(inside, first + i, 0)] if len(hashed) else np.zeros(len(first), dtype=np.uint64)
        h = np.where(inside, mix64(h ^ part) * np.uint64(0xD6E8FEB86659FD93), h)
    return mix64(h), begin


def sets_of(text: pa.Array, words: int) -> list[np.ndarray]:
    """The distinct shingle hashes of each text, ascending."""
    h, begin = shingle_hashes(text, words)
    return [np.unique(h[a:z], sorted=True) for a, z in zip(begin[:-1].tolist(), begin[1:].tolist())]


def _lists(arrays: list[np.ndarray]) -> pa.Array:
    ends = np.concatenate([[0], np.cumsum([len(a) for a in arrays])]).astype(np.int32)
    return pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate([*arrays, np.zeros(0, dtype=np.uint64)]).view(np.int64)))


def sketches(docs: DataFrame, id_col: str, text_col: str, words: int) -> DataFrame:
    """__id, __text_hash, n (set size), s1, s2 (a 128-bit digest of the set), sketch (ascending as unsigned)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text"):
            sets = sets_of(texts(piece), words)
            s1 = np.array([np.bitwise_xor.reduce(mix64(s)) if len(s) else 0 for s in sets], dtype=np.uint64).view(np.int64)
            s2 = np.array([s.sum(dtype=np.uint64) for s in sets], dtype=np.uint64).view(np.int64)
            yield pa.RecordBatch.from_arrays([piece.column("__id"), piece.column("__text_hash"), pa.array([len(s) for s in sets], pa.int64()), pa.array(s1), pa.array(s2), _lists([s[:SKETCH] for s in sets])], names=["__id", "__text_hash", "n", "s1", "s2", "sketch"])

    return docs.select(*document_key(id_col, text_col), F.col(text_col).alias("text")).mapInArrow(run, "__id long, __text_hash long, n long, s1 long, s2 long, sketch array<long>")


def whole_groups(batches: Iterator[pa.RecordBatch], keys: list[str]) -> Iterator[pa.Table]:
    """The groups of rows that are sorted by keys, one table each."""
    held: list[pa.RecordBatch] = []
    last = None
    for b in batches:
        if not b.num_rows:
            continue
        columns = [b.column(k).to_numpy(zero_copy_only=False) for k in keys]
        change = np.zeros(b.num_rows - 1, dtype=bool)
        for c in columns:
            change |= c[1:] != c[:-1]
        edges = [0, *(np.nonzero(change)[0] + 1).tolist(), b.num_rows]
        for a, z in zip(edges[:-1], edges[1:]):
            key = tuple(c[a] for c in columns)
            if held and key != last:
                yield pa.Table.from_batches(held)
                held = []
            held.append(b.slice(a, z - a))
            last = key
    if held:
        yield pa.Table.from_batches(held)


def spanning_links(ids: np.ndarray, similar) -> list[tuple[int, int]]:
    """Links that join each component of `similar` to one member, by a search that compares each
    reached member with the members not reached yet only. similar(x, rest) -> mask over rest.

    Sets of one id (an id that repeats with other texts) count as one node at the end.
    """
    rest = np.arange(len(ids))
    out = []
    while len(rest) > 1:
        root, rest = rest[0], rest[1:]
        queue = [root]
        while queue and len(rest):
            x = queue.pop()
            hit = similar(x, rest)
            if hit.any():
                found = rest[hit]
                rest = rest[~hit]
                out.extend((int(ids[root]), int(ids[y])) for y in found if ids[root] != ids[y])
                queue.extend(found.tolist())
    return out


def _segments(flat: np.ndarray, offsets: np.ndarray, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """The values of some rows in a row, and where each begins."""
    size = offsets[rows + 1] - offsets[rows]
    begin = np.concatenate([[0], np.cumsum(size)])
    return flat[np.repeat(offsets[rows] - begin[:-1], size) + np.arange(int(begin[-1]))], begin


def alike_by_sketch(flat: np.ndarray, offsets: np.ndarray, sizes: np.ndarray, least: float):
    """similar(x, rest) by the union-sketch estimate, which has to be at least `least`.

    Both sketches hold every value of their sets up to the smaller of their largest values (all values
    where a set is no larger than a sketch); over those the share of common values estimates Jaccard.
    """
    whole = sizes <= np.diff(offsets)
    top = np.where(whole, np.uint64(2**64 - 1), flat[offsets[1:] - 1])

    def similar(x: int, rest: np.ndarray) -> np.ndarray:
        own = flat[offsets[x] : offsets[x + 1]]
        values, begin = _segments(flat, offsets, rest)
        limit = np.minimum(top[rest], top[x])
        row = np.repeat(np.arange(len(rest)), np.diff(begin))
        below = values <= limit[row]
        place = np.minimum(np.searchsorted(own, values), len(own) - 1)
        common = np.bincount(row[below & (own[place] == values)], minlength=len(rest))
        theirs = np.bincount(row[below], minlength=len(rest))
        mine = np.searchsorted(own, limit, side="right")
        return common >= least * (mine + theirs - common)

    return similar


def alike_exactly(flat: np.ndarray, offsets: np.ndarray, percent: int):
    """similar(x, rest): 100 * intersection >= percent * union, on full sets."""
    size = np.diff(offsets)

    def similar(x: int, rest: np.ndarray) -> np.ndarray:
        out = (100 * np.minimum(size[rest], size[x]) >= percent * np.maximum(size[rest], size[x])) & (size[rest] > 0)
        near = rest[out]
        if len(near):
            own = flat[offsets[x] : offsets[x + 1]]
            values, begin = _segments(flat, offsets, near)
            place = np.minimum(np.searchsorted(own, values), len(own) - 1)
            same = np.concatenate([[0], np.cumsum(own[place] == values)])
            common = same[begin[1:]] - same[begin[:-1]]
            out[out] = 100 * common >= percent * (size[near] + size[x] - common)
        return out

    return similar


def joining_links(ids: np.ndarray, label: np.ndarray, role: np.ndarray, similar) -> list[tuple[int, int]]:
    """Links of probes (role 1 or 2) to members (role 0 or 2) that aren't in one component yet.

    A probe that finds members of another component is tied to one of them, and the two count as one
    component from then on; members of its own component are not compared.
    """
    label, out = label.copy(), []
    member = role != 1
    for x in np.nonzero(role > 0)[0]:
        rest = np.nonzero(member & (label != label[x]))[0]
        if not len(rest):
            continue
        for y in rest[similar(x, rest)]:
            if label[y] != label[x]:
                out.append((int(ids[x]), int(ids[y])))
                label[label == label[y]] = label[x]
    return out


def _searched(rows: DataFrame, keys: list[str], values: str, search) -> DataFrame:
    """Links a, b that `search` finds among the rows of each group of keys."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for g in whole_groups(batches, keys):
            if g.num_rows < 2:
                continue
            flat, offsets = _array(g, values)
            found = search(g, flat, offsets)
            if found:
                yield pa.RecordBatch.from_arrays(list(map(pa.array, np.array(found, dtype=np.int64).T)), names=["a", "b"])

    return rows.repartition(*keys).sortWithinPartitions(*keys, "id").mapInArrow(run, "a long, b long")


def in_chunks(rows: DataFrame, key: str) -> DataFrame:
    """Deals each group of `key` to chunks: adds `chunk`; rows: key, id, w (share of a chunk) and others.

    A group's least id is in each of its chunks, so that groups of copies of one text come together here.
    """
    sizes = rows.groupBy(key).agg(F.ceil(F.sum("w")).cast("long").alias("chunks"), F.min("id").alias("pivot"), F.count(F.lit(1)).alias("size")).where("size > 1").drop("size")
    own = F.pmod(F.xxhash64("id"), F.col("chunks"))
    chunk = F.when(F.col("id") == F.col("pivot"), F.sequence(F.lit(0).cast("long"), F.col("chunks") - 1)).otherwise(F.array(own))
    return rows.join(sizes, key).withColumn("chunk", F.explode(chunk)).drop("chunks", "pivot", "w")


def local_links(dealt: DataFrame, key: str, values: str, similar) -> DataFrame:
    """Spanning links inside each chunk of each group."""
    return _searched(dealt, [key, "chunk"], values, lambda g, flat, offsets: spanning_links(g["id"].to_numpy(), similar(g, flat, offsets)))


def open_groups(rows: DataFrame, key: str) -> DataFrame:
    """key, local_chunks, chunks, probe_chunks, top: the groups that hold several components, and the one with most members.

    Only members outside `top` have to be compared with all others: those in it are linked already.
    """
    sizes = rows.groupBy(key, "component").agg(F.sum("w").alias("w"), F.count(F.lit(1)).alias("n"))
    by = sizes.groupBy(key).agg(F.sum("w").alias("w"), F.max(F.struct("n", "component", "w")).alias("top"), F.count(F.lit(1)).alias("parts")).where("parts > 1")
    chunks = lambda w: F.greatest(F.ceil(w / WIDER), F.lit(1)).cast("long")
    return by.select(key, F.ceil("w").cast("long").alias("local_chunks"), chunks(F.col("w")).alias("chunks"), chunks(F.col("w") - F.col("top.w")).alias("probe_chunks"), F.col("top.component").alias("top"))


def across_chunks(rows: DataFrame, key: str) -> DataFrame:
    """Deals members and probes of open groups: adds c1, c2, role; rows: key, id, component, chunks, probe_chunks, top and others.

    Members go once to each chunk of probes, probes once to each chunk of members: no pair is left out
    but those whose two sides are in the group's largest component.
    """
    probe = F.col("component") != F.col("top")
    upto = lambda c: F.sequence(F.lit(0).cast("long"), F.col(c) - 1)
    own, at = F.pmod(F.xxhash64("id"), F.col("chunks")), F.pmod(F.xxhash64(F.lit(5), "id"), F.col("probe_chunks"))
    single = (F.col("chunks") == 1) & (F.col("probe_chunks") == 1)
    as_member = F.transform(upto("probe_chunks"), lambda b: F.struct(own.alias("c1"), b.alias("c2"), F.when(single & probe, 2).otherwise(0).alias("role")))
    as_probe = F.when(probe & ~single, F.transform(upto("chunks"), lambda a: F.struct(a.alias("c1"), at.alias("c2"), F.lit(1).alias("role")))).otherwise(F.expr("CAST(array() AS ARRAY<STRUCT<c1: BIGINT, c2: BIGINT, role: INT>>)"))
    return rows.withColumn("to", F.explode(F.concat(as_member, as_probe))).select("*", "to.*").drop("to", "chunks", "local_chunks", "probe_chunks", "top", "w")


def crossing_links(dealt: DataFrame, key: str, values: str, similar) -> DataFrame:
    """Links between the components of each group."""
    return _searched(dealt, [key, "c1", "c2"], values, lambda g, flat, offsets: joining_links(g["id"].to_numpy(), g["component"].to_numpy(), g["role"].to_numpy(), similar(g, flat, offsets)))


def _array(table: pa.Table, name: str) -> tuple[np.ndarray, np.ndarray]:
    column = table.column(name).combine_chunks()
    column = column.chunk(0) if isinstance(column, pa.ChunkedArray) else column
    offsets = column.offsets.to_numpy().astype(np.int64)
    return column.flatten().to_numpy(zero_copy_only=False).view(np.uint64), offsets - offsets[0]


def member_filter(members: DataFrame, keys: list[str]) -> tuple[np.ndarray, Column]:
    """A bitset of hashed keys, and the column of a row's bit: rows whose bit is off are no members.

    Its size is bounded (FILTER_BITS) whatever the number of members; a full one only lets more rows through.
    """
    n = members.count()
    bits = 1 << min(FILTER_BITS, max(12, (16 * n).bit_length()))
    slot = F.pmod(F.xxhash64(F.lit(77), *keys), F.lit(bits))
    words = members.select(slot.alias("s")).groupBy(F.expr("s div 64").alias("w")).agg(F.bit_or(F.expr("shiftleft(1L, CAST(s % 64 AS INT))")).alias("b")).toArrow()
    out = np.zeros(bits // 64, dtype=np.uint64)
    out[words["w"].to_numpy()] = words["b"].to_numpy().view(np.uint64)
    return out, slot


def _labelled(rows: DataFrame, found: DataFrame) -> DataFrame:
    """Adds the component of each id; an id without a link is its own."""
    return rows.join(found.select(F.col("node").alias("id"), "component"), "id", "left").withColumn("component", F.coalesce("component", "id"))


def loose_components(spark: SparkSession, members: DataFrame, percent: int) -> DataFrame:
    """node, component over pairs that share enough of their sketches; members: id, n, s1, s2, sketch.

    Inverted lists hold, for each class, those of its smallest values that are rarest: if two sets
    share enough of their values, they share one of these. So a passage or shingle that is in very
    many documents gives no list for documents that have other content.
    First each class is looked up in the lists of its two smallest shared values alone, chunk by chunk.
    That joins groups of copies, so of the other lists only those that still hold several components
    are dealt out with their sketches.
    """
    entries = members.select("id", "s1", "s2", F.least(F.size("sketch"), F.lit(INDEXED)).alias("k"), F.explode(F.slice("sketch", 1, INDEXED)).alias("v"))
    counts = materialise(spark, entries.groupBy("v").agg(F.count(F.lit(1)).alias("c")).where("c > 1"), "value-counts")
    shared = entries.join(counts, "v").groupBy("id", "s1", "s2", "k").agg(F.sort_array(F.collect_list(F.struct("c", "v"))).alias("own"))
    # what is in no other sketch comes first in the order and finds no partner
    need = F.element_at(F.array(*(F.lit(shared_values(k, percent)) for k in range(1, INDEXED + 1))), F.col("k").cast("int"))
    prefix = F.col("k") - need + 1 - (F.col("k") - F.size("own"))
    taken = materialise(spark, shared.withColumn("take", prefix).where("take > 0").select("id", "s1", "s2", F.slice("own.v", F.lit(1), F.col("take")).alias("vs"), F.slice(F.array_sort("own.v"), 1, 2).alias("least")), "lists")
    listed = lambda c: taken.select("id", "s1", "s2", F.explode(c).alias("v"), F.lit(1.0 / CHUNK).alias("w"))
    least = shared_values(SKETCH, percent) / SKETCH
    payload = members.select("id", "s1", "s2", "n", "sketch")
    similar = lambda g, flat, offsets: alike_by_sketch(flat, offsets, g["n"].to_numpy(), least)
    first = in_chunks(listed("least"), "v").join(payload, ["id", "s1", "s2"])
    found = components(spark, local_links(first, "v", "sketch", similar))
    labelled = materialise(spark, _labelled(listed("vs"), found), "labelled-lists")
    crossing = across_chunks(labelled.join(open_groups(labelled, "v"), "v"), "v").join(payload, ["id", "s1", "s2"])
    more = crossing_links(crossing, "v", "sketch", similar)
    return components(spark, found.select(F.col("node").alias("a"), F.col("component").alias("b")).unionAll(more))


def prefix_components(spark: SparkSession, docs: DataFrame, members: DataFrame, words: int, percent: int, id_col: str, text_col: str) -> DataFrame:
    """node, component without any chance of a miss: sets that may reach the limit share one of the
    smallest n - ceil(percent * n / 100) + 1 hashes of their full sets. All classes of a list are joined."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for piece in slices(batches, "text"):
            heads = [s[: len(s) - -(-percent * len(s) // 100) + 1] for s in sets_of(texts(piece), words)]
            size = [len(h) for h in heads]
            row = pa.array(np.repeat(np.arange(len(heads)), size))
            yield pa.RecordBatch.from_arrays([piece.column("__id").take(row), piece.column("__text_hash").take(row), pa.array(np.concatenate([*heads, np.zeros(0, dtype=np.uint64)]).view(np.int64))], names=["__id", "__text_hash", "v"])

    named = members.select(F.col("id").alias("__id"), "__text_hash")
    rows = docs.select(*document_key(id_col, text_col), F.col(text_col).alias("text")).join(named, ["__id", "__text_hash"], "left_semi").mapInArrow(run, "__id long, __text_hash long, v long")
    rows = materialise(spark, rows.select(F.col("__id").alias("id"), "v"), "prefixes")
    first = rows.groupBy("v").agg(F.min("id").alias("b"), F.max("id").alias("z")).where("b < z").drop("z")
    return components(spark, rows.join(first, "v").select(F.col("id").alias("a"), "b").where("a != b"))


def near_classes(spark: SparkSession, docs: DataFrame, words: int, percent: int, id_col: str = "doc_id", text_col: str = "text", exact: bool = False) -> tuple[DataFrame, DataFrame]:
    """Sketch table of all documents, and the component of each class of equal sets: s1, s2, n, component.

    1. Equal sets collapse to the least id, whatever their number.
    2. Loose components by shared sketch values (`loose_components`); a pair at the limit is missed with a
       chance of 2 * LOST at most, for sets that hold one another (a text cut short) as for others.
       exact: by prefixes of the full sets instead, without that chance, for more shuffled hashes.
    3. In each loose component, full sets are compared exactly, chunk by chunk: first inside chunks and
       with the least member, then what is not in the largest component with all members.
    No list or component is capped.
    """
    table = materialise(spark, sketches(docs, id_col, text_col, words), "sketches")
    classes = table.where("n > 0").groupBy("s1", "s2", "n").agg(F.min("__id").alias("id"))
    classes = materialise(spark, classes, "classes")
    members = table.select("s1", "s2", "n", F.col("__id").alias("id"), "__text_hash", "sketch").join(classes, ["s1", "s2", "n", "id"], "left_semi").dropDuplicates(["s1", "s2", "id"])
    members = materialise(spark, members, "members")
    loose = prefix_components(spark, docs, members, words, percent, id_col, text_col) if exact else loose_components(spark, members, percent)
    weight = F.greatest(F.lit(1.0 / CHUNK), F.col("n") / CHUNK_SHINGLES).alias("w")
    wanted = materialise(spark, members.select("id", "__text_hash", weight).join(loose.select(F.col("node").alias("id"), F.col("component").alias("cluster")), "id"), "clusters")

    def sets(rows: DataFrame, dealt: DataFrame) -> DataFrame:
        """dealt with the full sets of the documents in rows; texts stay where they are."""
        keyed = dealt.withColumnRenamed("id", "__id")
        bits, slot = member_filter(rows.withColumnRenamed("id", "__id"), ["__id", "__text_hash"])
        filter_ = spark.sparkContext.broadcast(bits)

        def full(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for piece in slices(batches, "text"):
                at = piece.column("slot").to_numpy()
                maybe = filter_.value[at >> 6] >> (at & 63).astype(np.uint64) & np.uint64(1)
                piece = piece.filter(pa.array(maybe == 1))
                if piece.num_rows:
                    yield pa.RecordBatch.from_arrays([piece.column("__id"), piece.column("__text_hash"), _lists(sets_of(texts(piece), words))], names=["__id", "__text_hash", "shingles"])

        source = docs.select(*document_key(id_col, text_col), F.col(text_col).alias("text")).withColumn("slot", slot)
        found = source.mapInArrow(full, "__id long, __text_hash long, shingles array<long>").dropDuplicates(["__id", "__text_hash"])
        return found.join(keyed, ["__id", "__text_hash"]).drop("__text_hash").withColumnRenamed("__id", "id")

    similar = lambda g, flat, offsets: alike_exactly(flat, offsets, percent)
    linked = components(spark, local_links(sets(wanted, in_chunks(wanted, "cluster")), "cluster", "shingles", similar))
    labelled = _labelled(wanted, linked)
    broken = materialise(spark, labelled.join(open_groups(labelled, "cluster").where("local_chunks > 1"), "cluster"), "open-clusters")
    if not broken.isEmpty():
        more = crossing_links(sets(broken, across_chunks(broken, "cluster")), "cluster", "shingles", similar)
        linked = components(spark, linked.select(F.col("node").alias("a"), F.col("component").alias("b")).unionAll(more))
    found = classes.join(linked.select(F.col("node").alias("id"), "component"), "id", "left").select("s1", "s2", "n", F.coalesce("component", "id").alias("component"))
    return table, materialise(spark, found, "components")


def near_components(spark: SparkSession, docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", exact: bool = False) -> DataFrame:
    """One row a document: doc_id, n_shingles, component_id (least id reachable over links), kept.

    Linked: 100 * shared distinct shingles >= percent * all, over lower-case (A-Z) word shingles.
    Null, empty or blank texts have no shingle, link with nothing and are kept. Rows that repeat an id
    share its node. Null ids count as the least id and come back as null. Other columns of docs, of
    whatever name, are not looked at; an empty table gives no row. exact: see `near_classes`.
    """
    table, found = near_classes(spark, docs, words, percent, id_col, text_col, exact)
    joined = table.select("__id", "__text_hash", "n", "s1", "s2").join(found, ["s1", "s2", "n"], "left").withColumn("component", F.coalesce("component", "__id"))
    real = lambda c: F.when(F.col(c) != -(1 << 63), F.col(c))
    return joined.select(real("__id").alias("doc_id"), F.col("n").alias("n_shingles"), real("component").alias("component_id"), (F.col("__id") == F.col("component")).alias("kept"), "__text_hash")


def keep_one_of_each(spark: SparkSession, docs: DataFrame, words: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", exact: bool = False) -> DataFrame:
    """The rows of docs whose id is the least of their component, with all their columns, whatever these are named.

    Rows that agree in id and text are one document and stay together. Null ids rank first; null, empty
    and blank texts stay; an empty table stays empty.
    """
    table, found = near_classes(spark, docs, words, percent, id_col, text_col, exact)
    joined = table.select("__id", "__text_hash", "n", "s1", "s2").join(found, ["s1", "s2", "n"], "left")
    gone = joined.where(F.col("component").isNotNull() & (F.col("component") != F.col("__id"))).select("__id", "__text_hash").distinct()
    return packed(docs, id_col, text_col).join(gone, ["__id", "__text_hash"], "left_anti").select("__doc.*")
