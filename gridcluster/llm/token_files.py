"""Token-ID output: word-aligned packing of ids into 64-bit words, in block-indexed binary files."""

from __future__ import annotations

import atexit
import struct
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyarrow import fs
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from ..session import discard, materialise, shared_dir
from .bpe_pieces import encoder_of
from .common import slices, texts

# Fixed values of the code: for each 4-bit selector, values a word and bits a value (60 payload bits).
# Selector 0 is the escape here: its word is followed by one raw 64-bit value.
COUNTS = (1, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1)
WIDTHS = (64, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60)
BLOCK = 1024
MAGIC = b"TOKW0001"
_FOOTER = struct.Struct("<QQQQ8s")
#: Ids in a file, about; a file holds whole documents.
FILE_IDS = 16_000_000


def _choices(values: np.ndarray, block: int) -> np.ndarray:
    """For each position the selector with most values that all fit and end within their block."""
    n = len(values)
    choice = np.full(n, 15, dtype=np.int8)
    top = int(values.max())
    if top >= 1 << 60:
        choice[values >= np.uint64(1 << 60)] = 0
    # maxima of up to 120 values from each position on; behind a block's end stands what fits nowhere
    rows = -(-n // block)
    kind = np.uint16 if top < 1 << 16 else np.uint32 if top < 1 << 32 else np.uint64
    limit = np.iinfo(kind).max
    longest = np.full(rows * block, limit, dtype=kind)
    longest[:n] = values
    longest = longest.reshape(rows, block)
    length = 1
    for sel in range(14, 0, -1):
        count, width = COUNTS[sel], WIDTHS[sel]
        if count > block:
            break
        while length < count:
            step = min(length, count - length)
            longest, length = np.maximum(longest[:, :-step], longest[:, step:]), length + step
        fits = np.zeros((rows, block), dtype=bool)
        fits[:, : block - count + 1] = longest <= min((1 << width) - 1, limit)
        fits = fits.reshape(-1)[:n]
        fits[max(0, n - count + 1) :] = False
        if not fits.any():
            break  # more values of fewer bits fit nowhere either
        choice[fits] = sel
    return choice


def pack(values: np.ndarray, block: int = BLOCK) -> tuple[np.ndarray, np.ndarray]:
    """64-bit words for the values, and the word offset at which each block of values begins.

    At every position the selector with most values that all fit is found at once, by running maxima of
    growing length; then all blocks step from word to word side by side. No word crosses a block.
    """
    n = len(values)
    if not n:
        return np.zeros(0, dtype=np.uint64), np.zeros(0, dtype=np.int64)
    choice = np.concatenate([_choices(values[a : a + 64 * block], block) for a in range(0, n, 64 * block)])
    values = values.astype(np.uint64, copy=False)
    steps = np.array(COUNTS, dtype=np.int64)[choice]
    at, ends = np.arange(0, n, block), np.minimum(np.arange(0, n, block) + block, n)
    order, live, starts = [], np.arange(len(at)), at.copy()
    owner = []
    while len(live):
        here = starts[live]
        order.append(here)
        owner.append(live)
        starts[live] = here + steps[here]
        live = live[starts[live] < ends[live]]
    first = np.sort(np.concatenate(order))
    chosen = choice[first]
    cells = np.where(chosen == 0, 2, 1)
    place = np.cumsum(cells) - cells
    words = np.zeros(int(cells.sum()), dtype=np.uint64)
    for sel in np.unique(chosen):
        mine = chosen == sel
        if sel == 0:
            words[place[mine] + 1] = values[first[mine]]
            continue
        count, width = COUNTS[sel], WIDTHS[sel]
        out = np.full(int(mine.sum()), np.uint64(int(sel) << 60), dtype=np.uint64)
        if width:
            for i in range(count):
                out |= values[first[mine] + i] << np.uint64(i * width)
        words[place[mine]] = out
    return words, place[np.searchsorted(first, at)]


def unpack(words: np.ndarray) -> np.ndarray:
    """The values of packed words, a selector at a time."""
    words = words.astype(np.uint64, copy=False)
    sel = (words >> np.uint64(60)).astype(np.int64)
    escaped = np.nonzero(sel == 0)[0]
    payload = np.zeros(len(words), dtype=bool)
    for i in escaped:  # a raw value may itself look like an escape
        if not payload[i]:
            payload[i + 1] = True
    counts = np.where(payload, 0, np.array(COUNTS, dtype=np.int64)[sel])
    begin = np.cumsum(counts) - counts
    out = np.zeros(int(counts.sum()), dtype=np.uint64)
    for s in np.unique(sel[~payload]):
        mine = np.nonzero((sel == s) & ~payload)[0]
        if s == 0:
            out[begin[mine]] = words[mine + 1]
        elif WIDTHS[s]:
            shifts = np.arange(COUNTS[s], dtype=np.uint64) * np.uint64(WIDTHS[s])
            got = words[mine][:, None] >> shifts & np.uint64((1 << WIDTHS[s]) - 1)
            out[begin[mine][:, None] + np.arange(COUNTS[s])] = got
    return out


class FileWriter:
    """words | block offsets | doc ids | doc lengths | footer. Only whole blocks are written before the end."""

    def __init__(self, files: fs.FileSystem, path: str):
        self.out, self.path = files.open_output_stream(path), path
        self.rest = np.zeros(0, dtype=np.uint32)
        self.n_words = self.n_ids = 0
        self.offsets: list[np.ndarray] = []
        self.docs: list[np.ndarray] = []
        self.lengths: list[np.ndarray] = []

    def add(self, doc_ids: np.ndarray, lengths: np.ndarray, ids: np.ndarray) -> None:
        self.docs.append(doc_ids)
        self.lengths.append(lengths)
        self.n_ids += len(ids)
        ids = np.concatenate([self.rest, ids])
        whole = len(ids) // BLOCK * BLOCK
        self._write(ids[:whole])
        self.rest = ids[whole:]

    def _write(self, ids: np.ndarray) -> None:
        words, offsets = pack(ids)
        self.offsets.append(offsets + self.n_words)
        self.n_words += len(words)
        self.out.write(words.astype("<u8").tobytes())

    def close(self) -> None:
        self._write(self.rest)
        docs = np.concatenate([*self.docs, np.zeros(0, dtype=np.int64)])
        offsets = np.concatenate([*self.offsets, np.zeros(0, dtype=np.int64)])
        for x in (offsets, docs, np.concatenate([*self.lengths, np.zeros(0, dtype=np.int64)])):
            self.out.write(x.astype("<i8").tobytes())
        self.out.write(_FOOTER.pack(self.n_words, len(offsets), len(docs), self.n_ids, MAGIC))
        self.out.close()


class FileReader:
    """Reads any run of blocks, or whole documents in order."""

    def __init__(self, files: fs.FileSystem, path: str):
        self.file = files.open_input_file(path)
        size = self.file.size()
        self.n_words, self.n_blocks, self.n_docs, self.n_ids, magic = _FOOTER.unpack(self.file.read_at(_FOOTER.size, size - _FOOTER.size))
        if magic != MAGIC:
            raise ValueError(f"{path} is no token file")
        at = 8 * self.n_words
        self.offsets = np.frombuffer(self.file.read_at(8 * self.n_blocks, at), dtype="<i8")
        self.doc_ids = np.frombuffer(self.file.read_at(8 * self.n_docs, at := at + 8 * self.n_blocks), dtype="<i8")
        self.lengths = np.frombuffer(self.file.read_at(8 * self.n_docs, at + 8 * self.n_docs), dtype="<i8")

    def blocks(self, first: int, last: int) -> np.ndarray:
        """The ids of blocks first..last-1."""
        a = self.offsets[first]
        b = self.offsets[last] if last < self.n_blocks else self.n_words
        return unpack(np.frombuffer(self.file.read_at(int(8 * (b - a)), int(8 * a)), dtype="<u8"))

    def ids(self, start: int, stop: int) -> np.ndarray:
        if start >= stop:
            return np.zeros(0, dtype=np.uint64)
        first = start // BLOCK
        return self.blocks(first, min(self.n_blocks, -(-stop // BLOCK)))[start - first * BLOCK : stop - first * BLOCK]


def encode_to_files(spark: SparkSession, docs: DataFrame, tokenizer: bytes, end_id: int = 0, id_col: str = "doc_id", text_col: str = "text", files: int | None = None, root: str | None = None) -> DataFrame:
    """Tokenizes every text, appends end_id, and writes the ids in ascending id order (null ids first).

    Files hold ascending ranges of ids that don't overlap but at an id that repeats. A task writes under a name of its own attempt, so a
    lost or repeated task leaves no half file in the manifest. Null text: the end id alone. Rows that repeat
    an id are written one after another; other columns are not looked at; an empty table gives no file.
    The folder goes when the session's process ends (`keep` it by naming one in `root`).
    Returns the manifest: part, piece, path, n_docs, n_ids.
    """
    if root is None:
        root = f"{shared_dir(spark)}/tokens-{uuid.uuid4().hex}"
        atexit.register(discard, spark, root)
    shared = spark.sparkContext.broadcast(tokenizer)  # a vocabulary file: a few MB, whatever the data

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, part = encoder_of(shared.value), TaskContext.get().partitionId()
        where, base = fs.FileSystem.from_uri(root)
        where.create_dir(base, recursive=True)
        piece, out, made = 0, None, []

        def finish():
            nonlocal out, piece
            out.close()
            made.append((part, piece, f"{root}/{out.path.rsplit('/', 1)[1]}", sum(map(len, out.docs)), out.n_ids))
            out, piece = None, piece + 1

        for s in slices(batches, "text", 6 << 20):
            lengths, ids = encoder.encode(texts(s), end_id)
            out = out or FileWriter(where, f"{base}/{part:06d}-{piece:04d}-{uuid.uuid4().hex[:12]}.tok")
            out.add(s.column("doc_id").fill_null(-(1 << 63)).to_numpy(), lengths, ids)
            if out.n_ids >= FILE_IDS:
                finish()
        if out:
            finish()
        yield pa.RecordBatch.from_pylist([dict(zip(("part", "piece", "path", "n_docs", "n_ids"), m)) for m in made], schema=pa.schema([("part", pa.int32()), ("piece", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64())]))

    # ranges are cut by id, then by a hash of the text, then anywhere: rows of one id needn't fit one task
    rows = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), F.xxhash64(text_col).alias("h"), F.monotonically_increasing_id().alias("m"))
    by = [F.col("doc_id").asc_nulls_first(), "h", "m"]
    ranged = rows.repartitionByRange(files, *by) if files else rows.repartitionByRange(*by)
    made = ranged.sortWithinPartitions(*by).mapInArrow(write, "part int, piece int, path string, n_docs long, n_ids long")
    return materialise(spark, made, "token-manifest")


def read_files(manifest: DataFrame, tasks: int) -> DataFrame:
    """One row a document from the files: doc_id, start (ids before it), n_tokens, ids_crc32 and the file.

    Null and repeated ids come back as they were written; an empty manifest gives no row.
    """
    before = Window.orderBy("part", "piece").rowsBetween(Window.unboundedPreceding, -1)
    listed = manifest.withColumn("start", F.coalesce(F.sum("n_ids").over(before), F.lit(0))).repartition(tasks, "path")

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for row in b.to_pylist():
                where, path = fs.FileSystem.from_uri(row["path"])
                f = FileReader(where, path)
                ends = np.cumsum(f.lengths)
                at = 0
                while at < f.n_docs:
                    base = int(ends[at - 1]) if at else 0
                    to = max(at + 1, int(np.searchsorted(ends, base + 1_000_000, side="right")))
                    ids = f.ids(base, int(ends[to - 1])).astype("<u4")
                    starts = ends[at:to] - f.lengths[at:to]
                    crc = [zlib.crc32(ids[a - base : z - base]) for a, z in zip(starts.tolist(), ends[at:to].tolist())]
                    doc = f.doc_ids[at:to]
                    yield pa.RecordBatch.from_arrays([pa.array(doc, mask=doc == -(1 << 63)), pa.array(starts + row["start"]), pa.array(f.lengths[at:to].astype(np.int64)), pa.array(crc, pa.int64()), pa.array([row["path"]] * (to - at))], names=["doc_id", "start", "n_tokens", "ids_crc32", "file"])
                    at = to

    return listed.mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long, file string")
