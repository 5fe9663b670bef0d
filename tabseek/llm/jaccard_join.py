"""Jaccard join on word shingles by prefixes of token combinations.

A document is the set of its distinct 3-word shingles; two link when their
similarity reaches the threshold. The result names each document's component.

1. Documents of equal sets are one set from here on.
2. Shingles are split into a rare and a frequent class by counts over all
   documents. Which class a shingle has decides only how it is indexed, so a
   bitmap of hashed frequent shingles is enough, whatever it mistakes. Its size
   follows their number, within bounds.
3. Order all shingles: rare ones first, each class by hash. A set of size n
   that reaches the threshold with another misses at most ``t`` of its own
   shingles there. Its prefix runs until ``t + 1`` is earned: each rare shingle
   earns one and is indexed alone; frequent shingles fall into subclasses, where
   each but the first earns one, and every two of a subclass are indexed as a
   combination. A pair that links misses too few to lose all that was earned,
   so it shares a rare shingle or a combination. The number of subclasses grows
   with the size band of the set; a set is indexed in each band in which it can
   have partners.
4. In each index entry, the members are verified against the one that shares most
   entries with others. What links becomes components, so that large groups of
   near copies cost one comparison a member.
5. What remains are members of one entry in different components: all pairs of
   those are held against size and a parity sketch, whose distance bounds the
   overlap, large entries in blocks of bounded size; survivors are verified.

6. Links lie inside components. The sets of a component are dealt to parts of
   bounded size, every two parts meet in one task, and what leaves it is a number
   a set: how many documents it links with. So all links between different texts
   are counted, though no pair is written.

Verification is exact on the sets' hashes. Nothing but the bitmaps, of
``2 ** MOST_BITS`` bits at most, comes to the driver or is broadcast.

Defined cases: a null or empty text, or one without words, has no shingles and
is its own component; a text of fewer than three words is one shingle; A-Z count
as a-z; rows of null doc_id have no component; repeated rows are equal sets, and
rows of one doc_id with different texts are one document, which links by any of
them; a text of any length is one set, read in slices of words; an empty table
gives no rows; other columns, whatever their names, are not read. ``keep_one``
keeps all columns as they are, and takes rows of one doc_id with different texts
as different documents.
"""

from __future__ import annotations

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, functions as F

from .store import discard, free_prefix, materialise
from .words import mix, text_slices, word_hashes, word_spans

WIDTH = 3
#: Two sets link when DEN * intersection >= NUM * union.
NUM, DEN = 90, 100
#: A shingle is frequent when more documents than this have it near their start in hash order.
FREQUENT = 10
#: Sizes of bitmaps, as powers of two: 2 MB to 32 MB.
LEAST_BITS, MOST_BITS = 24, 28
#: Members of one entry that are held against each other in one block.
BLOCK = 1024
#: Shingles of a part of a component, about; two parts meet in one task.
LINK_SHINGLES = 1 << 18
#: Entries of so many members or fewer give their pairs as rows.
SMALL = 16
_M = np.uint64(0x9E3779B97F4A7C15)


def text_sets(column: pa.Array, width: int = WIDTH):
    """Yield (row, sorted distinct shingle hashes) of each text that has words."""
    for row, end, data, offsets in text_slices(column):
        starts, ends, first = word_spans(data, offsets)
        words = word_hashes(data, starts, ends)
        whole = np.full(max(len(words) - width + 1, 0), np.uint64(width))
        for i in range(width if len(whole) else 0):
            whole = mix(whole * _M + words[i : i + len(whole)])
        for k, (a, b) in enumerate(zip(first[:-1].tolist(), first[1:].tolist())):
            if b - a >= width:
                yield row + k, np.unique(whole[a : b - width + 1])
            elif b > a:
                short = np.full(1, np.uint64(b - a))
                for w in words[a:b]:
                    short = mix(short * _M + w)
                yield row + k, short


def set_key(tokens: np.ndarray) -> int:
    """A 64-bit name of a set, as a signed number."""
    folded = np.add.reduce(mix(tokens), keepdims=True) ^ (np.bitwise_xor.reduce(tokens, keepdims=True) * _M)
    return int(mix(folded + np.uint64(len(tokens))).view(np.int64)[0])


def misses(n: int) -> int:
    """The most shingles of a set of size n that a linked set can lack."""
    return n - (NUM * n + DEN - 1) // DEN


def sketch_words(n):
    """64-bit words in the sketch of a set of size n: two bits a shingle or more, a power of two."""
    return 1 << np.maximum(np.ceil(np.log2(np.maximum(n, 1) / 32.0)), 0).astype(np.int64)


def sketch(tokens: np.ndarray) -> bytes:
    """Parities of hashed positions: a shingle that one of two sets lacks moves one bit at most.

    Sizes are powers of two and positions nest, so that a sketch folds to half its size.
    """
    bits = 64 * int(sketch_words(len(tokens)))
    odd = np.bincount((tokens & np.uint64(bits - 1)).astype(np.int64), minlength=bits) & 1
    return np.packbits(odd.astype(np.uint8)).tobytes()


def may_link(n, m, apart):
    """Whether sets of sizes n and m can link whose sketches differ in ``apart`` bits."""
    most = (n + m - apart) // 2
    return DEN * most >= NUM * (n + m - most)


def _longs(values) -> pa.Array:
    return pa.array(values, pa.int64())


def document_sets(docs: DataFrame) -> DataFrame:
    """Per row of ``docs``: doc_id, n, set_id and sketch (null without words)."""

    def run(batches):
        for batch in batches:
            n, ids, sketches = [0] * batch.num_rows, [None] * batch.num_rows, [None] * batch.num_rows
            for row, tokens in text_sets(batch.column("text")):
                n[row], ids[row], sketches[row] = len(tokens), set_key(tokens), sketch(tokens)
            yield pa.RecordBatch.from_arrays([batch.column("doc_id"), _longs(n), _longs(ids), pa.array(sketches, pa.binary())], ["doc_id", "n", "set_id", "sketch"])

    return docs.mapInArrow(run, "doc_id long, n long, set_id long, sketch binary")


def _bitmap(keys: DataFrame) -> np.ndarray:
    """A bitmap with the hashes of ``keys`` (column ``at``, a long) set: 16 bits a key if the bounds allow; of that size at the driver.

    Only the low bits of a hash count.
    """
    bits = min(max((16 * keys.count()).bit_length(), LEAST_BITS), MOST_BITS)
    slot = F.col("at").bitwiseAND(F.lit((1 << bits) - 1)) + 1
    parts = keys.select(F.bitmap_bucket_number(slot).alias("bucket"), F.bitmap_bit_position(slot).alias("bit")).groupBy("bucket").agg(F.bitmap_construct_agg("bit").alias("part"))
    size = 4096
    out = np.zeros((1 << bits) // 8, np.uint8)
    for row in parts.toLocalIterator():  # 2 ** bits / 32768 rows at most
        at = (row.bucket - 1) * size
        out[at : at + size] = np.frombuffer(row.part, np.uint8)
    return out


def _in_bitmap(bitmap: np.ndarray, hashes: np.ndarray) -> np.ndarray:
    at = hashes.view(np.int64) & (8 * len(bitmap) - 1)
    return (bitmap[at >> 3] >> (at & 7).astype(np.uint8)) & 1 == 1


def frequent_bitmap(docs: DataFrame, frequent: int = FREQUENT) -> np.ndarray:
    """Hashed shingles that more than ``frequent`` documents have in twice the prefix they need.

    Counts are sums over all documents by 32-bit hash, pre-summed in each batch.
    """

    def run(batches):
        for batch in batches:
            held = [np.zeros(0, np.uint64)]
            for _, tokens in text_sets(batch.column("text")):
                held.append(tokens[: max(100, 2 * misses(len(tokens)) + 10)])
            slots, counts = np.unique((np.concatenate(held) & np.uint64(0xFFFFFFFF)).astype(np.uint32), return_counts=True)
            yield pa.RecordBatch.from_arrays([pa.array(slots.view(np.int32)), pa.array(counts.astype(np.int32))], ["slot", "n"])

    counted = docs.mapInArrow(run, "slot int, n int").groupBy("slot").agg(F.sum("n").alias("n")).where(F.col("n") > frequent)
    counted = materialise(counted.select(F.col("slot").cast("long").alias("at")), "frequent")
    bitmap = _bitmap(counted)
    discard(counted)
    return bitmap


def signatures(tokens: np.ndarray, bitmap: np.ndarray) -> np.ndarray:
    """The index entries of a set (sorted distinct shingle hashes); see the module's step 3."""
    n = len(tokens)
    if n < 2:
        return np.zeros(0, np.uint64)  # links with its equal only
    goal = misses(n) + 1
    often = _in_bitmap(bitmap, tokens)
    rare = tokens[~often][:goal]
    if len(rare) == goal:
        return rare
    common = tokens[often]
    out = [rare]
    smallest, largest = (NUM * n + DEN - 1) // DEN, DEN * n // NUM
    for band in range(smallest.bit_length() - 1, largest.bit_length()):
        subclasses = max(1, (1 << band) // 16)
        kind = (common >> np.uint64(32)) % np.uint64(subclasses)
        first = np.zeros(len(common), dtype=bool)
        first[np.unique(kind, return_index=True)[1]] = True
        earned = len(rare) + np.cumsum(~first)
        end = int(np.searchsorted(earned, goal)) + 1
        order = np.argsort(kind[:end], kind="stable")
        kinds, chosen = kind[:end][order], common[:end][order]
        for gap in range(1, len(chosen)):
            same = kinds[gap:] == kinds[:-gap]
            if not same.any():
                break
            out.append(mix(mix(chosen[:-gap][same] + np.uint64(band)) * _M + chosen[gap:][same]))
    return np.concatenate(out)


def index_entries(docs: DataFrame, bitmap: np.ndarray) -> DataFrame:
    """(entry, set_id) of all documents' sets, distinct within a batch."""
    shared = docs.sparkSession.sparkContext.broadcast(bitmap)

    def run(batches):
        bits = shared.value
        for batch in batches:
            seen, entries, ids = set(), [np.zeros(0, np.uint64)], [np.zeros(0, np.int64)]
            for _, tokens in text_sets(batch.column("text")):
                key = set_key(tokens)
                if key not in seen:
                    seen.add(key)
                    found = signatures(tokens, bits)
                    entries.append(found)
                    ids.append(np.full(len(found), key, np.int64))
            yield pa.RecordBatch.from_arrays([_longs(np.concatenate(entries).view(np.int64)), _longs(np.concatenate(ids))], ["entry", "set_id"])

    return docs.mapInArrow(run, "entry long, set_id long")


def _unlike(pairs: DataFrame, sets: DataFrame) -> DataFrame:
    """``pairs`` without those whose sketches show that they can't link."""

    def run(batches):
        for batch in batches:
            keep = []
            for n, m, x, y in zip(*(batch.column(c).to_pylist() for c in ("n", "m", "x", "y"))):
                x, y = (np.frombuffer(v, np.uint64)[None, :] for v in (x, y))
                while x.shape[1] > y.shape[1]:
                    x = _fold(x)
                while y.shape[1] > x.shape[1]:
                    y = _fold(y)
                keep.append(bool(may_link(n, m, int(np.bitwise_count(x ^ y).sum()))))
            yield batch.filter(pa.array(keep, pa.bool_())).select(["a", "b"])

    left = sets.select(F.col("id").alias("a"), "n", F.col("sketch").alias("x"))
    right = sets.select(F.col("id").alias("b"), F.col("n").alias("m"), F.col("sketch").alias("y"))
    return pairs.join(left, "a").join(right, "b").mapInArrow(run, "a long, b long")


def _token_sets(docs: DataFrame, shared) -> DataFrame:
    """(doc_id, set_id, tokens) of the texts whose doc_id is in a broadcast bitmap, and of some others."""

    def build(batches):
        for batch in batches:
            part = batch.filter(pa.array(_in_bitmap(shared.value, np.asarray(batch.column("slot")))))
            rows, keys, sets = [], [], []
            for row, tokens in text_sets(part.column("text")):
                rows.append(row)
                keys.append(set_key(tokens))
                # six of eight bytes: still no two of a pair's shingles are alike by chance
                sets.append(tokens.astype(">u8").view(np.uint8).reshape(-1, 8)[:, :6].tobytes())
            yield pa.RecordBatch.from_arrays([part.column("doc_id").take(pa.array(rows, pa.int64())), _longs(keys), pa.array(sets, pa.binary())], ["doc_id", "set_id", "tokens"])

    return docs.where("doc_id IS NOT NULL").select("doc_id", "text", F.xxhash64("doc_id").alias("slot")).mapInArrow(build, "doc_id long, set_id long, tokens binary")


def linked(pairs: DataFrame, docs: DataFrame) -> DataFrame:
    """The (a, b) of ``pairs`` (doc_ids) whose sets link, by exact intersection.

    Sets of documents outside the pairs are not built: a bitmap of the ids
    selects the texts; what it selects in vain finds no partner.
    """
    spark = docs.sparkSession
    ids = materialise(pairs.select(F.explode(F.array("a", "b")).alias("id")).distinct(), "paired-ids")
    shared = spark.sparkContext.broadcast(_bitmap(ids.select(F.xxhash64("id").alias("at"))))

    sets = _token_sets(docs, shared).select(F.col("doc_id").alias("id"), "tokens")
    sets = materialise(sets.join(ids, "id", "left_semi"), "candidate-sets")
    discard(ids)

    def verify(batches):
        for batch in batches:
            keep = []
            for x, y in zip(batch.column("x").to_pylist(), batch.column("y").to_pylist()):
                n, m = len(x) // 6, len(y) // 6
                both = _overlap(x, y)
                keep.append(DEN * both >= NUM * (n + m - both))
            yield batch.filter(pa.array(keep, pa.bool_())).select(["a", "b"])

    left = sets.select(F.col("id").alias("a"), F.col("tokens").alias("x"))
    right = sets.select(F.col("id").alias("b"), F.col("tokens").alias("y"))
    return pairs.select("a", "b").join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(verify, "a long, b long")


def _numbers(raw: bytes) -> np.ndarray:
    wide = np.zeros((len(raw) // 6, 8), np.uint8)
    wide[:, 2:] = np.frombuffer(raw, np.uint8).reshape(-1, 6)
    return wide.view(">u8").ravel().astype(np.uint64)


def _overlap(x: bytes, y: bytes) -> int:
    a, b = _numbers(x), _numbers(y)
    merged = np.sort(np.concatenate((a, b)))
    return int(np.count_nonzero(merged[1:] == merged[:-1]))


def components(edges: DataFrame) -> DataFrame:
    """(id, component): the smallest id reachable over ``edges`` (a, b), for ids that have any.

    Stars are rewired towards smaller ids until nothing changes; every round's
    edges are written to shared storage. Minima are summed before their shuffle,
    and a hot id's edges meet one row, so its partition can be split.
    """
    state = lambda e: tuple(e.agg(F.count("*"), F.sum(F.xxhash64("u", "v").cast("decimal(38,0)"))).first())
    now = materialise(edges.where("a <> b").select(F.greatest("a", "b").alias("u"), F.least("a", "b").alias("v")).distinct(), "edges")
    before = state(now)
    while before[0]:
        both = now.unionByName(now.select(F.col("v").alias("u"), F.col("u").alias("v")))
        least = both.groupBy("u").agg(F.least(F.min("v"), F.col("u")).alias("m"))
        wide = both.join(least, "u").where("v > u").select(F.col("v").alias("u"), F.col("m").alias("v")).where("u <> v").distinct()
        low = wide.groupBy("u").agg(F.min("v").alias("m"))
        narrow = wide.join(low, "u")
        old, now = now, materialise(narrow.where("v <> m").select(F.col("v").alias("u"), F.col("m").alias("v")).unionByName(low.select("u", F.col("m").alias("v"))).distinct(), "edges")
        discard(old)
        after = state(now)
        if after == before:
            break
        before = after
    return now.select(F.col("u").alias("id"), F.col("v").alias("component")).unionByName(now.select(F.col("v").alias("id"), F.col("v").alias("component")).distinct())


def _fold(bits: np.ndarray) -> np.ndarray:
    half = bits.shape[1] // 2
    return bits[:, :half] ^ bits[:, half:]


def _group_pairs(ids, label, n, part, raw, two_parts: bool) -> set[tuple[int, int]]:
    """Pairs of one block that may link: sketches of one size directly, of twice the size folded."""
    found, size = set(), sketch_words(n)
    for s in np.unique(size):
        own, larger = np.flatnonzero(size == s), np.flatnonzero(size == 2 * s)
        bits = np.frombuffer(b"".join(raw[i] for i in own), np.uint64).reshape(-1, s)
        if len(larger):
            bits = np.concatenate((bits, _fold(np.frombuffer(b"".join(raw[i] for i in larger), np.uint64).reshape(-1, 2 * s))))
        at = np.concatenate((own, larger))
        for k in range(len(own)):
            rest = at[k + 1 :]
            ok = label[rest] != label[own[k]]
            if two_parts:  # pairs inside a part come in that part's own block
                ok &= part[rest] != part[own[k]]
            ok &= DEN * np.minimum(n[rest], n[own[k]]) >= NUM * np.maximum(n[rest], n[own[k]])
            near = np.flatnonzero(ok)
            if len(near):
                apart = np.bitwise_count(bits[k + 1 + near] ^ bits[k]).sum(1).astype(np.int64)
                for o in near[may_link(n[rest[near]], n[own[k]], apart)]:
                    a, b = int(ids[own[k]]), int(ids[rest[o]])
                    found.add((min(a, b), max(a, b)))
    return found


def _sorted_groups(batches, keys: tuple[str, ...]):
    """Tables of whole groups from batches sorted by ``keys``, with the places where groups begin."""

    def changes(table: pa.Table) -> np.ndarray:
        columns = np.stack([table.column(c).to_numpy() for c in keys])
        return np.flatnonzero((columns[:, 1:] != columns[:, :-1]).any(0)) + 1

    held = None
    for batch in batches:
        table = pa.Table.from_batches([batch]) if held is None else pa.concat_tables([held, pa.Table.from_batches([batch])])
        cuts = changes(table) if table.num_rows > 1 else []
        if not len(cuts):
            held = table
            continue
        yield table.slice(0, cuts[-1]), [0, *cuts[:-1].tolist()]
        held = table.slice(cuts[-1])
    if held is not None and held.num_rows:
        yield held, [0]


def _block_pairs(batches):
    """Candidate (a, b) from rows sorted by block."""
    for table, starts in _sorted_groups(batches, ("entry", "i", "j")):
        i, j, *columns = (table.column(c).to_numpy() for c in ("i", "j", "id", "label", "n", "part"))
        raw = table.column("sketch").to_pylist()
        pairs = set()
        for s, e in zip(starts, [*starts[1:], table.num_rows]):
            pairs |= _group_pairs(*(c[s:e] for c in columns), raw[s:e], i[s] != j[s])
        a, b = zip(*pairs) if pairs else ((), ())
        yield pa.RecordBatch.from_arrays([_longs(a), _longs(b)], ["a", "b"])


def _count_links(sets: list[np.ndarray], part: np.ndarray, copies: np.ndarray, two_parts: bool) -> np.ndarray:
    """For each set of a block the copies of the sets it links with; across parts only if there are two."""
    m, n = len(sets), np.array([len(t) for t in sets])
    row = np.repeat(np.arange(m), n)
    names, at, seen = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    twice = seen > 1  # what one set alone has is in no overlap
    row, at = row[twice[at]], (np.cumsum(twice) - 1)[at[twice[at]]]
    words = max(1, -(-int(twice.sum()) // 64))
    bits = np.zeros(m * words * 8, np.uint8)
    np.bitwise_or.at(bits, row * words * 8 + (at >> 3), (1 << (at & 7)).astype(np.uint8))
    bits = bits.reshape(m, -1).view(np.uint64)
    out = np.zeros(m, np.int64)
    for k in range(m - 1):
        rest = np.arange(k + 1, m)
        ok = DEN * np.minimum(n[rest], n[k]) >= NUM * np.maximum(n[rest], n[k])
        if two_parts:  # pairs inside a part come in that part's own block
            ok &= part[rest] != part[k]
        rest = rest[ok]
        both = np.bitwise_count(bits[rest] & bits[k]).sum(1, dtype=np.int64)
        rest = rest[DEN * both >= NUM * (n[rest] + n[k] - both)]
        out[k] += copies[rest].sum()
        out[rest] += copies[k]
    return out


def link_counts(sets: DataFrame, component: DataFrame, docs: DataFrame) -> DataFrame:
    """(set_id, links): the documents with other texts that each set of ``sets`` (set_id, id, n, n_copies) links with.

    ``component`` (id, component) names those that link at all. Work and rows grow
    with the square of a component's parts, as its links can; a part's sets are
    the unit that a task holds.
    """

    def count(batches):
        for table, starts in _sorted_groups(batches, ("component", "i", "j")):
            i, j, part, copies = (table.column(c).to_numpy() for c in ("i", "j", "part", "n_copies"))
            tokens = [_numbers(t) for t in table.column("tokens").to_pylist()]
            found = [_count_links(tokens[s:e], part[s:e], copies[s:e], i[s] != j[s]) for s, e in zip(starts, [*starts[1:], table.num_rows])]
            yield pa.RecordBatch.from_arrays([table.column("set_id").combine_chunks(), _longs(np.concatenate(found))], ["set_id", "links"])

    members = sets.join(component, "id").select("set_id", "id", "component", "n", "n_copies")
    size = members.groupBy("component").agg(F.sum("n").alias("total"), F.count("*").alias("size")).where("size > 1")
    members = materialise(members.join(size, "component").withColumn("parts", F.ceil(F.col("total") / LINK_SHINGLES).cast("int")).drop("total", "size"), "component-members")
    shared = docs.sparkSession.sparkContext.broadcast(_bitmap(members.select(F.xxhash64("id").alias("at"))))
    # a set is built from its first document; rows that repeat it meet already where they are read
    built = _token_sets(docs, shared).join(members.select("set_id", F.col("id").alias("doc_id")), ["set_id", "doc_id"], "left_semi")
    tokens = built.groupBy("set_id").agg(F.first("tokens").alias("tokens"))
    part = F.pmod(F.hash("set_id"), F.col("parts"))
    blocks = members.withColumn("part", part).join(tokens, "set_id").withColumn("other", F.explode(F.sequence(F.lit(0), F.col("parts") - 1)))
    blocks = blocks.select("component", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "set_id", "n_copies", "tokens")
    counted = blocks.repartition("component", "i", "j").sortWithinPartitions("component", "i", "j").mapInArrow(count, "set_id long, links long")
    return counted.groupBy("set_id").agg(F.sum("links").alias("links"))


def join(docs: DataFrame, frequent: int = FREQUENT, count_links: bool = True) -> DataFrame:
    """Per row of ``docs`` (doc_id, text): doc_id, n_shingles, component_id, n_copies and, unless declined, n_links.

    ``n_copies`` counts the rows of an equal set, ``n_links`` all other rows that
    the row links with, copies included; rows of null doc_id are not counted and
    have none. A row without shingles links with nothing.
    """
    docs = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = materialise(document_sets(docs), "document-sets")
    sets = rows.where("set_id IS NOT NULL AND doc_id IS NOT NULL").groupBy("set_id").agg(F.min("doc_id").alias("id"), F.count("*").alias("n_copies"), F.first("n").alias("n"), F.first("sketch").alias("sketch"))
    sets = materialise(sets, "distinct-sets")
    small = sets.select("set_id", "id", "n")
    entries = materialise(index_entries(docs.where("doc_id IS NOT NULL"), frequent_bitmap(docs, frequent)), "entries")
    # entries of one set only lead nowhere; most are of this kind
    shared = entries.groupBy("entry").agg(F.min("set_id").alias("lo"), F.max("set_id").alias("hi"), F.count("*").alias("size")).where("lo <> hi").select("entry", "size")
    members = entries.join(shared, "entry").distinct().join(small, "set_id").select("entry", "size", "id", "n")
    members = materialise(members, "members")
    discard(entries)
    # the member that shares most leads; comparisons with it are one a member
    weight = members.groupBy("id").agg(F.sum("size").alias("weight"))
    weighed = members.join(weight, "id")
    leads = weighed.groupBy("entry").agg(F.max(F.struct("weight", "id", "n")).alias("lead"))
    fits = f"{DEN} * least(n, m) >= {NUM} * greatest(n, m)"
    star = members.join(leads.select("entry", F.col("lead.weight").alias("weight"), F.col("lead.id").alias("lead"), F.col("lead.n").alias("m")), "entry").where(f"id <> lead AND {fits}")
    first = star.groupBy("id").agg(F.max(F.struct("weight", "lead")).alias("best")).select(F.least("id", "best.lead").alias("a"), F.greatest("id", "best.lead").alias("b")).distinct()
    stars = materialise(_unlike(first, sets), "star-pairs")
    known = materialise(linked(stars, docs), "star-links")
    labels = materialise(components(known), "star-components")
    # entries whose members are not all of one component
    labelled = materialise(members.join(labels, "id", "left").select("entry", "id", "n", F.coalesce("component", "id").alias("label")), "labelled")
    discard(stars, members, labels)
    mixed = labelled.groupBy("entry").agg(F.min("label").alias("lo"), F.max("label").alias("hi"), F.count("*").alias("size")).where("lo <> hi").select("entry", "size")
    left = labelled.join(mixed, "entry")
    # small entries: pairs, each of which meets in many entries, are made distinct before sketches join them
    x = left.where(F.col("size") <= SMALL).select("entry", F.col("id").alias("a"), "n", F.col("label").alias("label_a"))
    y = x.select("entry", F.col("a").alias("b"), F.col("n").alias("m"), F.col("label_a").alias("label_b"))
    few = _unlike(x.join(y, "entry").where(f"a < b AND label_a <> label_b AND {fits}").select("a", "b").distinct(), sets)
    # large ones: blocks of bounded size, from which only survivors come
    parts = F.ceil(F.col("size") / BLOCK).cast("int")
    blocks = left.where(F.col("size") > SMALL).join(sets.select("id", "sketch"), "id").withColumn("part", F.pmod(F.hash("id"), parts)).withColumn("other", F.explode(F.sequence(F.lit(0), parts - 1)))
    blocks = blocks.select("entry", F.least("part", "other").alias("i"), F.greatest("part", "other").alias("j"), "part", "id", "label", "n", "sketch")
    many = blocks.repartition("entry", "i", "j").sortWithinPartitions("entry", "i", "j").mapInArrow(_block_pairs, "a long, b long")
    rest = few.unionByName(many).distinct()
    rest = materialise(rest, "block-pairs")
    discard(labelled)
    final = components(known.unionByName(linked(rest, docs)))
    discard(known, rest)
    found = sets.join(final, "id", "left").select("set_id", F.coalesce("component", "id").alias("component"), "n_copies")
    has_id = F.col("doc_id").isNotNull()
    columns = ["doc_id", F.col("n").alias("n_shingles"), F.when(has_id, F.coalesce("component", "doc_id")).alias("component_id"), F.coalesce("n_copies", F.lit(1)).alias("n_copies")]
    if count_links:
        found = found.join(link_counts(sets, final, docs), "set_id", "left")
        columns.append(F.when(has_id, F.coalesce(F.col("n_copies") - 1 + F.coalesce("links", F.lit(0)), F.lit(0))).alias("n_links"))
    return rows.join(found, "set_id", "left").select(*columns)


def keep_one(docs: DataFrame, **options) -> DataFrame:
    """``docs`` with one row of each group of linked documents, that of the smallest doc_id; rows of null doc_id stay.

    Rows of one doc_id and text are one document; with different texts they are
    different ones, each of which stays or goes by its own links.
    """
    own = free_prefix(docs.columns)
    key, flag = f"{own}key", f"{own}again"
    again = materialise(docs.where("doc_id IS NOT NULL").groupBy("doc_id").count().where("count > 1").select("doc_id"), "repeated-ids")
    if again.isEmpty():
        doomed = join(docs.select("doc_id", "text"), count_links=False, **options).where("component_id <> doc_id").select("doc_id")
        return docs.join(doomed, "doc_id", "left_anti").select(*docs.columns)
    # a row of a repeated doc_id is named by a negative number from its text
    known = again.select(F.col("doc_id").alias(f"{own}id"), F.lit(True).alias(flag))
    named = docs.join(known, F.col("doc_id") == F.col(f"{own}id"), "left")
    number = F.when(F.col(flag), -1 - F.shiftrightunsigned(F.xxhash64("doc_id", "text"), 1)).otherwise(F.col("doc_id").cast("long"))
    named = named.withColumn(key, F.when(F.col("doc_id").isNotNull(), number))
    ids = named.where(F.col(key).isNotNull()).select(F.col(key).alias("doc_id"), F.col("doc_id").alias("id")).distinct()
    found = join(named.select(F.col(key).alias("doc_id"), "text"), count_links=False, **options).select("doc_id", "component_id").distinct()
    stays = found.join(ids, "doc_id").groupBy("component_id").agg(F.min(F.struct("id", "doc_id")).alias("least")).select(F.col("least.doc_id").alias(key))
    kept = named.join(stays, key, "left_semi")
    once = kept.where(F.col(flag)).dropDuplicates([key])
    parts = [kept.where(F.col(flag).isNull()), once, named.where("doc_id IS NULL")]
    return parts[0].select(*docs.columns).unionByName(parts[1].select(*docs.columns)).unionByName(parts[2].select(*docs.columns))


def brute_force(texts: dict[int, str | None]) -> dict[int, int]:
    """Components by comparing all pairs, for tests."""
    return brute_force_links(texts)[0]


def brute_force_links(texts: dict[int, str | None]) -> tuple[dict[int, int], dict[int, int]]:
    """(components, numbers of links) by comparing all pairs, for tests."""
    bags = {}
    for doc_id, text in texts.items():
        words = (text or "").encode().lower().split()
        bags[doc_id] = {tuple(words[i : i + WIDTH]) for i in range(max(len(words) - WIDTH + 1, 1))} if words else set()
    root, links = {d: d for d in texts}, dict.fromkeys(texts, 0)

    def find(d):
        while root[d] != d:
            d = root[d]
        return d

    ids = sorted(texts)
    for k, a in enumerate(ids):
        for b in ids[k + 1 :]:
            x, y = bags[a], bags[b]
            if x and y and DEN * min(len(x), len(y)) >= NUM * max(len(x), len(y)):
                both = len(x & y)
                if DEN * both >= NUM * (len(x) + len(y) - both):
                    links[a], links[b] = links[a] + 1, links[b] + 1
                    ra, rb = find(a), find(b)
                    root[max(ra, rb)] = min(ra, rb)
    return {d: find(d) for d in ids}, links
