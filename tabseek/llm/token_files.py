"""Token-id files: word-aligned packing of ids into 64-bit words.

Format of a shard (little-endian):

* magic ``TSI1``, then blocks of up to ``BLOCK`` ids each, each block a run of
  64-bit words. A word's high 4 bits select how many ids of which width its low
  60 bits hold (first id lowest). Selectors 0 and 1 hold 240 and 120 zeros;
  2-14 hold ids of 1 to 30 bits; 15 holds one id of up to 60 bits. An id of
  more than 60 bits is an escape: selector 15 with all 60 bits set, and the
  raw id in the next word. (An id equal to that mark is escaped too.)
* the block offsets, the doc_ids with null marks, and the id counts of the
  documents, all as 64-bit integers;
* a footer of four 64-bit integers: blocks, documents, ids, and where the
  offsets begin.

Documents lie in ascending doc_id order over all shards (null first), so the
place of a document's first id follows from counts alone.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .store import executor_fs, scratch_path, write_atomically
from .tokens import default_vocabulary, tokenizer

MAGIC = b"TSI1\0\0\0\0"
BLOCK = 1024
#: Bytes of input a shard, by the planner's estimate.
SHARD_BYTES = 1 << 28
#: Ids per word and bits per id of the sixteen selectors.
COUNTS = np.array([240, 120, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1])
WIDTHS = np.array([0, 0, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60])
_PAYLOAD = np.uint64((1 << 60) - 1)
_LARGEST = np.array([(1 << w) - 1 for w in WIDTHS.tolist()[:15]], np.uint64)


def encode_blocks(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """(words, first word of each block) of ids; blocks are packed side by side.

    Whether a selector fits at a place is found for all places at once; then all
    blocks advance together by one word per step.
    """
    ids = np.asarray(ids, dtype=np.uint64)
    n = len(ids)
    if n == 0:
        return np.zeros(0, np.uint64), np.zeros(0, np.int64)
    left = (BLOCK - np.arange(n) % BLOCK).astype(np.int16)
    left[n // BLOCK * BLOCK :] = np.arange(n % BLOCK, 0, -1)
    need = np.searchsorted(_LARGEST, ids).astype(np.int8)  # the narrowest selector that holds the id
    best = np.full(n, 15, np.int8)
    misfit = np.zeros(n + 1, np.int32)
    for s in range(14, -1, -1):
        count = int(COUNTS[s])
        if count > n or np.count_nonzero(need <= s) < count:
            continue
        np.cumsum(need > s, out=misfit[1:])
        fits = (misfit[count:] == misfit[:-count]) & (left[: n - count + 1] >= count)
        best[: n - count + 1][fits] = s
    at = np.arange(0, n, BLOCK)
    ends = np.minimum(at + BLOCK, n)
    live, steps = np.arange(len(at)), []
    while len(live):
        here = at[live]
        steps.append((live, here))
        at[live] = here + COUNTS[best[here]]
        live = live[at[live] < ends[live]]
    block = np.concatenate([b for b, _ in steps])
    place = np.concatenate([p for _, p in steps])
    place = np.sort(place)
    selector = best[place]
    words = selector.astype(np.uint64) << np.uint64(60)
    for s in range(2, 16):
        rows = np.flatnonzero(selector == s)
        start = place[rows]
        for j in range(COUNTS[s] if len(rows) else 0):
            words[rows] |= (ids[start + j] & _PAYLOAD) << np.uint64(j * int(WIDTHS[s]))
    escaped = np.flatnonzero((selector == 15) & (ids[place] >= _PAYLOAD))
    sizes = np.ones(len(place), np.int64)
    if len(escaped):
        words[escaped] = ~np.uint64(0)
        sizes[escaped] = 2
    first = np.concatenate(([0], np.cumsum(sizes)))
    out = np.zeros(first[-1], np.uint64)
    out[first[:-1]] = words
    out[first[:-1][escaped] + 1] = ids[place[escaped]]
    n_words = np.bincount(block, minlength=len(ends))
    block_word = np.concatenate(([0], np.cumsum(n_words)[:-1]))
    return out, first[block_word]


def decode_words(words: np.ndarray) -> np.ndarray:
    """The ids in a run of whole blocks."""
    words = np.asarray(words, dtype=np.uint64)
    marks = np.flatnonzero(words == ~np.uint64(0))
    raw = np.zeros(len(words), dtype=bool)
    taken = -1
    for i in marks:  # escapes are rare; a raw word may itself look like a mark
        if i > taken:
            raw[i + 1] = True
            taken = i + 1
    heads = np.flatnonzero(~raw)
    selector = (words[heads] >> np.uint64(60)).astype(np.int64)
    counts = COUNTS[selector]
    start = np.cumsum(counts) - counts
    out = np.zeros(int(counts.sum()), np.uint64)
    for s in range(2, 16):
        rows = np.flatnonzero(selector == s)
        mask = np.uint64((1 << int(WIDTHS[s])) - 1)
        for j in range(COUNTS[s] if len(rows) else 0):
            out[start[rows] + j] = (words[heads[rows]] >> np.uint64(j * int(WIDTHS[s]))) & mask
    if raw.any():
        escaped = np.isin(heads + 1, np.flatnonzero(raw))
        out[start[escaped]] = words[heads[escaped] + 1]
    return out


def _shard_chunks(batches: Iterator[pa.RecordBatch], vocabulary: str, end_id: int, totals: dict) -> Iterator[bytes]:
    """The bytes of a shard, block by block as documents arrive."""
    encode = tokenizer(vocabulary).encode_texts
    pending, held, n_words, n_ids = [], 0, 0, 0
    offsets: list[np.ndarray] = []
    docs: list[np.ndarray] = []
    nulls: list[np.ndarray] = []
    counts: list[np.ndarray] = []
    yield MAGIC

    def flush(final: bool):
        nonlocal pending, held, n_words
        ids = np.concatenate(pending) if pending else np.zeros(0, np.uint32)
        whole = len(ids) if final else len(ids) // BLOCK * BLOCK
        words, starts = encode_blocks(ids[:whole])
        offsets.append(starts + n_words)
        n_words += len(words)
        pending, held = [ids[whole:]], len(ids) - whole
        return words.astype("<u8").tobytes()

    for batch in batches:
        for _, _, ids, ends in encode(batch.column("text"), end_id):
            pending.append(ids)
            counts.append(np.diff(ends))
            held += len(ids)
            n_ids += len(ids)
            if held >= 64 * BLOCK:
                yield flush(False)
        column = batch.column("doc_id")
        docs.append(np.asarray(column.fill_null(0), dtype=np.int64))
        nulls.append(np.asarray(column.is_null(), dtype=np.int64))
    yield flush(True)
    parts = [np.concatenate(x).astype("<i8") if x else np.zeros(0, "<i8") for x in (offsets, docs, nulls, counts)]
    totals |= {"n_docs": len(parts[1]), "n_ids": n_ids}
    for part in parts:
        yield part.tobytes()
    yield np.array([len(parts[0]), len(parts[1]), n_ids, len(MAGIC) + 8 * n_words], "<i8").tobytes()


def read_shard(uri: str) -> Iterator[tuple[int | None, np.ndarray]]:
    """(doc_id, ids) of a shard's documents, decoding some blocks at a time."""
    fs, path = executor_fs(uri)
    with fs.open_input_file(path) as file:
        size = file.size()
        n_blocks, n_docs, _, at = np.frombuffer(file.read_at(32, size - 32), "<i8")
        index = np.frombuffer(file.read_at(8 * (n_blocks + 3 * n_docs), at), "<i8")
        if file.read_at(8, 0) != MAGIC:
            raise ValueError(f"{path} is no token-id file")
        offsets = np.append(index[:n_blocks], (at - len(MAGIC)) // 8)
        docs, nulls, counts = index[n_blocks:].reshape(3, n_docs)
        block, ready = 0, np.zeros(0, np.uint64)
        for doc, null, count in zip(docs.tolist(), nulls.tolist(), counts.tolist()):
            while len(ready) < count:
                to = min(block + max(256, (count - len(ready)) // BLOCK + 1), n_blocks)
                words = np.frombuffer(file.read_at(8 * (offsets[to] - offsets[block]), len(MAGIC) + 8 * offsets[block]), "<u8")
                ready, block = np.concatenate((ready, decode_words(words))), to
            yield None if null else doc, ready[:count]
            ready = ready[count:]


def write_token_files(docs: DataFrame, path: str, vocabulary: str | None = None, end_id: int = 2, n_shards: int | None = None) -> DataFrame:
    """Write all of ``docs`` (doc_id, text) below ``path``; one manifest row per shard.

    Rows: shard, path, n_docs, n_ids. A null text is empty and holds the end id
    alone. Rows of one doc_id stand side by side in the order of the input, over
    as many shards as they fill; null doc_ids come first. No rows give empty
    shards. Other columns, whatever their names, are not read. A repeated task
    attempt writes the same bytes under the same name. Shards follow the input's
    size, and are no fewer than the shuffle's partitions.
    """
    vocabulary = vocabulary or default_vocabulary()
    if not n_shards:
        size = int(str(docs._jdf.queryExecution().optimizedPlan().stats().sizeInBytes()))
        n_shards = max(int(docs.sparkSession.conf.get("spark.sql.shuffle.partitions")), min(-(-size // SHARD_BYTES), 1 << 20))

    def write(batches):
        from pyspark import TaskContext

        shard, totals = TaskContext.get().partitionId(), {}
        uri = f"{path}/shard-{shard:08d}.ids"
        write_atomically(uri, _shard_chunks(batches, vocabulary, end_id, totals))
        yield pa.RecordBatch.from_pydict({"shard": pa.array([shard], pa.int32()), "path": [uri], "n_docs": pa.array([totals["n_docs"]], pa.int64()), "n_ids": pa.array([totals["n_ids"]], pa.int64())})

    # the place in the input splits the rows of a hot doc_id
    numbered = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text", F.monotonically_increasing_id().alias("place"))
    ordered = numbered.repartitionByRange(n_shards, "doc_id", "place").sortWithinPartitions("doc_id", "place")
    return ordered.mapInArrow(write, "shard int, path string, n_docs long, n_ids long")


def read_token_files(manifest: DataFrame) -> DataFrame:
    """Per document of the shards: doc_id, start, n_tokens, ids_crc32.

    ``start`` counts the ids of all documents before it, over all shards. The
    manifest has one row per shard, so it alone comes to the driver.
    """
    spark = manifest.sparkSession
    rows = sorted(manifest.collect(), key=lambda r: r.shard)
    before = np.concatenate(([0], np.cumsum([r.n_ids for r in rows], dtype=np.int64))).tolist()
    shards = [(r.path, start) for r, start in zip(rows, before) if r.n_docs]
    schema = "doc_id long, start long, n_tokens long, ids_crc32 long"
    if not shards:
        return spark.createDataFrame([], schema)

    def read(frames):
        for frame in frames:
            for uri, start in zip(frame["path"], frame["first"]):
                found = []
                for doc, ids in read_shard(uri):
                    found.append((doc, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes())))
                    start += len(ids)
                    if len(found) == 50_000:
                        yield pd.DataFrame(found, columns=["doc_id", "start", "n_tokens", "ids_crc32"]).astype({"doc_id": "Int64"})
                        found = []
                yield pd.DataFrame(found, columns=["doc_id", "start", "n_tokens", "ids_crc32"]).astype({"doc_id": "Int64"})

    paths = spark.createDataFrame(shards, "path string, first long").repartition(len(shards))
    return paths.mapInPandas(read, schema)


def token_files(docs: DataFrame, path: str | None = None, **options) -> DataFrame:
    """Write ``docs`` as token-id files and read them back; see the two steps."""
    path = path or scratch_path(docs.sparkSession, "token-files")
    return read_token_files(write_token_files(docs, path, **options))
