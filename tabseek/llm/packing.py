"""Packing documents into fixed windows by multiway differencing.

Documents are tokenised where they are read; nothing is shuffled. What a document
holds beyond whole windows is a piece; short consecutive pieces go as one. Each
task gathers pieces until they hold ``GROUP_WINDOWS`` windows' worth of ids, then
partitions them: every piece starts as a partial partition (one window holding
it, the others empty), and the two partial partitions of the largest spread are
merged with opposing imbalances until one is left, whose windows are near equal.
Where a window exceeds the capacity, the window count rises and the pieces are
partitioned anew. Pieces stay whole unless that would waste more than ``waste``
of a group: then those longer than three quarters of a window are cut, then
those longer than three quarters of that, and so on.
"""

from __future__ import annotations

import heapq
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

from .tokens import default_vocabulary, tokenizer

CAPACITY = 4096
GROUP_WINDOWS = 256
#: A group ends at so many documents, however short.
GROUP_DOCUMENTS = 65_536
PIECE_SCHEMA = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, sequence_id long, offset long"


def difference(sizes: list[int], windows: int) -> list[list[int]]:
    """Partition item numbers into ``windows`` lists of near-equal total size."""

    def sums_of(spread: int, sums):
        if sums is None:  # an item by itself
            sums = np.zeros(windows, np.int64)
            sums[-1] = -spread
        return sums

    # a partial partition: its spread (negative), a number that breaks ties, its ascending sums above the least, and how it was made
    heap = [(-size, i, None, i) for i, size in enumerate(sizes)]
    heapq.heapify(heap)
    while len(heap) > 1:
        spread, tie, sums, made = heapq.heappop(heap)
        other_spread, _, other_sums, other_made = heap[0]
        total = sums_of(spread, sums) + sums_of(other_spread, other_sums)[::-1]
        order = total.argsort(kind="stable")
        total = total[order]
        total -= total[0]
        heapq.heapreplace(heap, (-int(total[-1]), tie, total, (made, other_made, order.astype(np.int32))))
    out = [[] for _ in range(windows)]
    # back down: which window stands at each place of a partial partition
    left = [(heap[0][3], np.arange(windows))] if heap else []
    while left:
        made, window = left.pop()
        if isinstance(made, tuple):
            before = np.empty_like(window)
            before[made[2]] = window
            left += [(made[0], before), (made[1], before[::-1])]
        else:
            out[window[-1]].append(made)
    return [sorted(items) for items in out]


def fitting(sizes: list[int], capacity: int = CAPACITY, most: int | None = None) -> list[list[int]] | None:
    """Lists of item numbers, each of at most ``capacity`` in all: as few as differencing finds; no item is larger.

    None if it takes more than ``most``.
    """
    count = -(-sum(sizes) // capacity)
    while count < len(sizes):
        if most is not None and count > most:
            return None
        windows = difference(sizes, count)
        over = sum(max(sum(sizes[i] for i in w) - capacity, 0) for w in windows)
        if not over:
            return [w for w in windows if w]
        count += -(-over // capacity)
    return [[i] for i in range(len(sizes))] if most is None or len(sizes) <= most else None


def fill(sizes: list[int], capacity: int = CAPACITY, waste: float = 0.01) -> list[list[tuple[int, int, int]]]:
    """Windows of (item, from, to), each of at most ``capacity``; every unit of every item once.

    Items up to ``capacity`` stay whole if at most ``waste`` of the windows are
    more than the items need; otherwise ever shorter ones are cut.
    """
    needed = -(-sum(sizes) // capacity)
    limit = capacity
    while True:
        pieces = [(i, at, min(at + limit, size)) for i, size in enumerate(sizes) for at in range(0, size, limit)]
        # at last the count rises as far as it must
        most = needed + int(waste * needed) if limit > capacity // 16 else None
        windows = fitting([to - at for _, at, to in pieces], capacity, most)
        if windows is not None:
            break
        limit = limit * 3 // 4
    out = []
    for window in windows:
        joined: list[tuple[int, int, int]] = []
        for item, at, to in sorted(pieces[p] for p in window):
            if joined and joined[-1][0] == item and joined[-1][2] == at:
                at = joined.pop()[1]
            joined.append((item, at, to))
        out.append(joined)
    return out


def pack(docs: DataFrame, vocabulary: str | None = None, end_id: int = 2, capacity: int = CAPACITY, group_windows: int = GROUP_WINDOWS, with_ids: bool = False) -> DataFrame:
    """Pieces of all ``docs`` (doc_id, text) and their places in sequences.

    A null text is empty and holds the end id alone, so every row gives at least
    one piece; repeated rows and null doc_ids are packed like others; a long text
    fills whole sequences, and its rest is a piece. No rows give no pieces.
    ``with_ids`` adds the piece's ids. Other columns, whatever their names, are
    not read. The last group of a task may leave a window's worth unfilled.
    """
    vocabulary = vocabulary or default_vocabulary()
    schema = PIECE_SCHEMA + (", ids array<int>" if with_ids else "")
    goal, short = capacity * group_windows, max(capacity // 64, 1)

    def row(doc_id, start: int, ids: np.ndarray, doc_tokens: int, sequence: int, offset: int) -> tuple:
        return (doc_id, start, len(ids), zlib.crc32(ids.astype("<u4").tobytes()), doc_tokens, sequence, offset) + ((ids,) if with_ids else ())

    def place(group: list, sequence: int) -> tuple[list, int]:
        # consecutive short documents are one item, which starts at these places
        sizes, members, rows = [], [], []
        for k, (_, _, ids, _) in enumerate(group):
            if sizes and sizes[-1] + len(ids) <= short:
                sizes[-1] += len(ids)
                members[-1].append(k)
            else:
                sizes.append(len(ids))
                members.append([k])
        for window in fill(sizes, capacity):
            offset = 0
            for item, at, to in window:
                begin = 0
                for k in members[item]:
                    doc_id, start, ids, doc_tokens = group[k]
                    low, high = max(at - begin, 0), min(to - begin, len(ids))
                    begin += len(ids)
                    if low < high:
                        rows.append(row(doc_id, start + low, ids[low:high], doc_tokens, sequence, offset))
                        offset += high - low
            sequence += 1
        return rows, sequence

    def as_batch(rows: list) -> pa.RecordBatch:
        names = [x.split()[0] for x in schema.split(", ")]
        columns = list(zip(*rows))
        arrays = [pa.array(c, pa.int64()) for c in columns[:7]]
        return pa.RecordBatch.from_arrays(arrays + [pa.array([x.astype(np.int32) for x in c], pa.list_(pa.int32())) for c in columns[7:]], names)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        encode = tokenizer(vocabulary).encode_texts
        sequence = TaskContext.get().partitionId() << 33
        group, held, out = [], 0, []
        for batch in batches:
            doc_ids = batch.column("doc_id").to_pylist()
            for first, end, all_ids, ends in encode(batch.column("text"), end_id):
                for doc_id, at, to in zip(doc_ids[first:end], ends[:-1].tolist(), ends[1:].tolist()):
                    size = to - at
                    whole = size - size % capacity
                    for start in range(0, whole, capacity):
                        out.append(row(doc_id, start, all_ids[at + start : at + start + capacity], size, sequence, 0))
                        sequence += 1
                    if whole < size:
                        group.append((doc_id, whole, all_ids[at + whole : to], size))
                        held += size - whole
                    if held >= goal or len(group) >= GROUP_DOCUMENTS:
                        rows, sequence = place(group, sequence)
                        out += rows
                        group, held = [], 0
                if len(out) > 5_000:
                    yield as_batch(out)
                    out = []
        out += place(group, sequence)[0]
        if out:
            yield as_batch(out)

    return docs.selectExpr("cast(doc_id as long) as doc_id", "text").mapInArrow(run, schema)
