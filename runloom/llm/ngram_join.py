"""N-gram Jaccard join: every link of similarity 0.75 or more between 5-word shingle sets, and its connected components.

1. Each text becomes its set of 56-bit shingle hashes. Equal sets share a 64-bit set id and are one node from there on.
2. Shingles are ordered rarest first by a fixed-size table of hashed counts over all sets. Of n shingles only the rarest
   quarter is sent out, and n / MEET more: two linked sets must then meet in several of them. A tile is one shingle with the
   sets sent to it, in bands of size; a set that stands in too few tiles has no link and goes no further.
3. Sets gather in families: under the band's first set that they meet most often, and its leaders. Families are cut into
   blocks of bounded size. Inside a block every pair is checked unless it is joined already.
4. Tiles that hold sets of several components and blocks are cut into blocks of TILE_BLOCK sets. A task takes a pair of blocks and
   compares all of its pairs that are still open by sizes, places and bitmaps; those that may link are checked exactly.
A check bounds the overlap from above by the differing bits of two parity bitmaps (where they differ, the sets differ in as
many elements at least), then intersects the sorted arrays exactly. Rows stay in proportion to the sets and the links
between components: pairs of a group are never written out.
"""

from __future__ import annotations

import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from runloom.llm.common import bit_filter, buffers, discard, passes, pieces, settle, texts, tidy, written
from runloom.llm.textnum import SPACED, mix, ngrams, same_text, words

SHINGLE = 5
#: Of n shingles, n // MEET more than needed are sent out: linked sets meet in that many tiles besides one.
MEET = 8
#: Bits of a set's bitmap.
BITMAP = 1024
#: Hashed counts that order the shingles: 4 MB a task, whatever the corpus.
COUNTERS = 1 << 22
_CHUNK = 1 << 16
#: Most sets and (but for one larger set) shingles of a family's block.
BLOCK_SETS, BLOCK_SHINGLES = 8192, 1 << 22
#: Times that families go up to their leaders' families: chains of up to 2^JUMPS leaders become one family.
JUMPS = 3
#: Sets of a tile that a task compares with as many others.
TILE_BLOCK = 8192
#: Pairs that two components of one pair of blocks have checked before the components are joined; the rest wait for that.
FIRST = 16
_LOW = np.uint64((1 << 56) - 1)


def shingle_sets(column: pa.Array, rarity: np.ndarray | None = None) -> Iterator[tuple[int, int, np.ndarray, np.ndarray]]:
    """For pieces of a null-free column: first and last row, borders of each text's shingles, and the shingles, distinct and sorted.

    Fewer than five words: the whole sequence. rarity: a level of every counter; shingles are then sorted by it first and
    hold it in their top byte.
    """
    for lo, hi in pieces(column):
        w = words(*buffers(column.slice(lo, hi - lo)), SPACED)
        count = np.diff(w.first)
        sizes = np.where(count >= SHINGLE, count - SHINGLE + 1, count > 0)
        first = np.concatenate([[0], np.cumsum(sizes)])
        x = np.empty(first[-1], np.uint64)
        whole = np.repeat(count >= SHINGLE, sizes)
        x[whole] = ngrams(w.hash, SHINGLE)[same_text(w, SHINGLE)]
        x[~whole] = [ngrams(w.hash[w.first[i] : w.first[i + 1]], count[i])[0] for i in np.flatnonzero((count > 0) & (count < SHINGLE))]
        x &= _LOW
        if rarity is not None:
            x |= rarity[(x & np.uint64(COUNTERS - 1)).astype(np.int64)].astype(np.uint64) << np.uint64(56)
        for a, b in zip(first[:-1].tolist(), first[1:].tolist()):
            x[a:b].sort()
        new = np.ones(len(x), bool)
        new[1:] = x[1:] != x[:-1]
        new[first[:-1][sizes > 0]] = True
        yield lo, hi, np.concatenate([[0], np.cumsum(new)])[first], x[new]


def set_ids(first: np.ndarray, x: np.ndarray) -> np.ndarray:
    """A 64-bit id of each set (0 where it is empty): equal for equal sets, different for others but for a chance of 2^-64 a pair."""
    sizes = np.diff(first)
    full = np.flatnonzero(sizes)
    out = np.zeros(len(sizes), np.int64)
    if len(full):
        x, starts = x & _LOW, first[:-1][full]
        total, odd = np.add.reduceat(mix(x), starts), np.bitwise_xor.reduceat(mix(~x), starts)
        out[full] = mix(mix(total + sizes[full].astype(np.uint64)) ^ odd).view(np.int64)
    return out


def bitmap(x: np.ndarray) -> np.ndarray:
    odd = np.bincount((x & np.uint64(BITMAP - 1)).astype(np.int64), minlength=BITMAP) & 1
    return np.packbits(odd.astype(np.uint8))


def _unseen(sid: np.ndarray, sizes: np.ndarray, seen: set[int]) -> np.ndarray:
    """True for the first of each set in this task."""
    out = np.zeros(len(sid), bool)
    for i in np.flatnonzero(sizes):
        if (key := int(sid[i])) not in seen:
            seen.add(key)
            out[i] = True
    return out


SET_SCHEMA = "doc_id {id_type}, text_hash long, n long, sid long, chunk int, counts binary"


def _sets(batches: Iterator[pa.RecordBatch], id_type: pa.DataType) -> Iterator[pa.RecordBatch]:
    """A row per document, and at the end the task's counters in chunks."""
    counters, seen = np.zeros(COUNTERS, np.uint32), set()
    types = [id_type, pa.int64(), pa.int64(), pa.int64(), pa.int32(), pa.binary()]
    names = ["doc_id", "text_hash", "n", "sid", "chunk", "counts"]
    for batch in batches:
        sizes, sids = [np.zeros(0, np.int64)], [np.zeros(0, np.int64)]
        for _, _, first, x in shingle_sets(texts(batch.column(2))):
            sizes.append(np.diff(first))
            sids.append(set_ids(first, x))
            fresh = _unseen(sids[-1], sizes[-1], seen)
            np.add.at(counters, (x[np.repeat(fresh, sizes[-1])] & np.uint64(COUNTERS - 1)).astype(np.int64), np.uint32(1))
        n, sid = np.concatenate(sizes), np.concatenate(sids)
        nothing = [pa.nulls(len(n), t) for t in types[4:]]
        yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), pa.array(n), pa.array(sid, mask=n == 0), *nothing], names)
    if seen:
        chunks = range(COUNTERS // _CHUNK)
        parts = [zlib.compress(np.minimum(counters[k * _CHUNK : (k + 1) * _CHUNK], 65535).astype(np.uint16).tobytes(), 1) for k in chunks]
        yield pa.RecordBatch.from_arrays([*(pa.nulls(len(chunks), t) for t in types[:4]), pa.array(chunks, pa.int32()), pa.array(parts, pa.binary())], names)
    tidy()


def _rarity(key: tuple, batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    total = np.zeros(_CHUNK, np.int64)
    for batch in batches:
        for x in batch.column("counts"):
            total += np.frombuffer(zlib.decompress(x.as_py()), np.uint16)
    level = np.minimum(8 * np.log2(np.maximum(total, 1)), 255).astype(np.uint8)
    yield pa.RecordBatch.from_arrays([pa.array([key[0].as_py()], pa.int32()), pa.array([level.tobytes()], pa.binary())], ["chunk", "levels"])


def rarity(sets: DataFrame) -> np.ndarray:
    """A level from 0 (rarest) to 255 of every counter, summed over all tasks: COUNTERS bytes."""
    rows = sets.filter("chunk is not null").select("chunk", "counts").groupBy("chunk").applyInArrow(_rarity, "chunk int, levels binary").collect()
    out = np.zeros(COUNTERS, np.uint8)
    for r in rows:
        out[r["chunk"] * _CHUNK : (r["chunk"] + 1) * _CHUNK] = np.frombuffer(r["levels"], np.uint8)
    return out


def _prefixes(batches: Iterator[pa.RecordBatch], levels) -> Iterator[pa.RecordBatch]:
    """token, sid, place: the rarest shingles of each set, once a task; place holds size band (top byte), size and rank (28 bits each)."""
    rare, seen = levels.value, set()
    for batch in batches:
        for _, _, first, x in shingle_sets(texts(batch.column(0)), rare):
            sizes, sid = np.diff(first), set_ids(first, x)
            keep = np.where(_unseen(sid, sizes, seen), np.minimum(sizes, sizes // 4 + 1 + sizes // MEET), 0)
            band = np.floor(np.log(np.maximum(sizes, 1)) / np.log(4 / 3) + 1e-9).astype(np.int64)
            rank = np.arange(len(x)) - np.repeat(first[:-1], sizes)
            rows = np.flatnonzero(rank < np.repeat(keep, sizes))
            place = np.repeat((band << 56) + (sizes << 28), sizes)[rows] + rank[rows]
            out = [x[rows].view(np.int64), np.repeat(sid, sizes)[rows], place]
            for k in range(0, len(rows), 1 << 18):
                yield pa.RecordBatch.from_arrays([pa.array(c[k : k + (1 << 18)]) for c in out], ["token", "sid", "place"])
    tidy()


def _tiles(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Rows of tiles with two sets or more, from rows ordered by token, band, sid: with the first set of their band, and their number in the tile.

    One row is held back between batches, so memory does not depend on the size of a tile.
    """
    held: tuple | None = None  # token, sid, place, in a tile with the row before, first of the band, number, leader
    names = ["token", "sid", "place", "leader", "number"]
    for batch in batches:
        cols = [batch.column(k).to_numpy() for k in range(3)]
        if held is not None:
            cols = [np.concatenate([[h], c]) for h, c in zip(held, cols)]
        token, sid, place = cols
        fresh = np.ones(len(token), bool)
        fresh[1:] = (token[1:] != token[:-1]) | (sid[1:] != sid[:-1])
        token, sid, place = token[fresh], sid[fresh], place[fresh]
        if not len(token):
            continue
        same = np.zeros(len(token), bool)
        same[1:] = token[1:] == token[:-1]
        band, at = place >> 56, np.arange(len(token))
        tile = ~same
        start = tile.copy()
        start[1:] |= band[1:] != band[:-1]
        head = np.maximum.accumulate(np.where(start, at, 0))
        leader = sid[head]
        number = at - np.maximum.accumulate(np.where(tile, at, 0))
        if held is not None:  # the tile and the band of row 0 began before
            same[0] = held[3]
            leader[: int(np.argmax(start[1:])) + 1 if start[1:].any() else None] = held[4]
        # a band's first set follows that of the band before, so that families reach over bands
        firsts = np.flatnonzero(start[1:] & ~tile[1:]) + 1
        firsts = firsts[band[firsts] == band[firsts - 1] + 1]
        follows = leader.copy()
        follows[firsts] = leader[firsts - 1]
        if held is not None:
            follows[0] = held[6]
            number[: int(np.argmax(tile[1:])) + 1 if tile[1:].any() else None] += held[5]
        many = same.copy()
        many[:-1] |= same[1:]
        rows = np.flatnonzero(many[:-1])
        if len(rows):
            yield pa.RecordBatch.from_arrays([pa.array(c[rows]) for c in (token, sid, place, follows, number)], names)
        held = (token[-1], sid[-1], place[-1], bool(same[-1]), leader[-1], number[-1], follows[-1])
    if held is not None and held[3]:
        yield pa.RecordBatch.from_arrays([pa.array([v], pa.int64()) for v in (held[0], held[1], held[2], held[6], held[5])], names)
    tidy()


def _arrays(batches: Iterator[pa.RecordBatch], wanted) -> Iterator[pa.RecordBatch]:
    """sid, bitmap and sorted shingles of the sets that the filter lets pass, once a task."""
    bits, seen = wanted.value, set()
    names = ["sid", "bits", "shingles"]
    for batch in batches:
        for _, _, first, x in shingle_sets(texts(batch.column(0))):
            sizes, sid = np.diff(first), set_ids(first, x)
            keep = np.flatnonzero(_unseen(sid, np.where(passes(bits, sid), sizes, 0), seen))
            parts = [x[first[i] : first[i + 1]] for i in keep]
            if parts:
                yield pa.RecordBatch.from_arrays([pa.array(sid[keep]), pa.array([bitmap(p).tobytes() for p in parts], pa.binary()), pa.array([p.tobytes() for p in parts], pa.binary())], names)
    tidy()


def _links(a: np.ndarray, b: np.ndarray) -> bool:
    """100 times the common elements are at least 75 times all elements, of two sorted arrays."""
    if len(a) > len(b):
        a, b = b, a
    place = np.searchsorted(b, a)
    common = int((b[np.minimum(place, len(b) - 1)] == a).sum())
    return 100 * common >= 75 * (len(a) + len(b) - common)


def joined(sid: np.ndarray, bits: np.ndarray, arrays: list[np.ndarray]) -> np.ndarray:
    """Component of each set of a block: the number of one of its sets. Every pair that sizes and bitmaps admit is checked unless joined already."""
    n = np.array([len(x) for x in arrays])
    order = np.argsort(n, kind="stable")
    label, lows = np.arange(len(sid)), np.searchsorted(n[order], -(-3 * n[order] // 4))
    for at, (i, low) in enumerate(zip(order, lows)):
        before = order[low:at]
        before = before[(sid[before] != sid[i]) & (label[before] != label[i])]
        differing = np.bitwise_count(bits[before] ^ bits[i]).sum(axis=1, dtype=np.int64)
        near = 7 * differing <= n[before] + n[i]
        before, differing = before[near], differing[near]
        before = before[np.argsort(differing, kind="stable")]
        while len(before):
            if _links(arrays[before[0]], arrays[i]):
                label[label == label[before[0]]] = label[i]
            before = before[1:]
            before = before[label[before] != label[i]]
    return label


def _block_links(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Links a, b that hold the components of each block together, from rows family, block, sid, bits, shingles ordered by block."""
    held: list[pa.RecordBatch] = []

    def found() -> pa.RecordBatch:
        rows = pa.Table.from_batches(held)
        sid = rows.column("sid").to_numpy()
        _, once = np.unique(sid, return_index=True)
        rows, sid = rows.take(once), sid[once]
        bits = np.frombuffer(b"".join(rows.column("bits").to_pylist()), np.uint64).reshape(len(sid), -1)
        label = joined(sid, bits, [np.frombuffer(x.as_buffer(), np.uint64) for chunk in rows.column("shingles").chunks for x in chunk])
        rest = np.flatnonzero(label != np.arange(len(sid)))
        return pa.RecordBatch.from_arrays([pa.array(sid[label[rest]]), pa.array(sid[rest])], ["a", "b"])

    key = None
    for batch in batches:
        family, block = batch.column(0).to_numpy(), batch.column(1).to_numpy()
        cuts = np.flatnonzero((family[1:] != family[:-1]) | (block[1:] != block[:-1])) + 1
        for a, b in zip([0, *cuts], [*cuts, len(family)]):
            if b > a:
                if key != (family[a], block[a]) and held:
                    yield found()
                    held = []
                key = (family[a], block[a])
                held.append(batch.slice(a, b - a))
    if held:
        yield found()
    tidy()


def _tile_pairs(batches: Iterator[pa.RecordBatch], limit: int | None) -> Iterator[pa.RecordBatch]:
    """Pairs a, b of different components that sizes, places and bitmaps admit, from rows of pairs of blocks, ordered by them.

    limit: of two components of one pair of blocks that many pairs, the nearest first; more: there are others.
    """
    held: list[pa.RecordBatch] = []

    def found(rows: pa.Table) -> Iterator[pa.RecordBatch]:
        token, i, j, block, sid, label, place, home = (rows.column(k).to_numpy() for k in range(8))
        group = np.concatenate([[0], np.cumsum((token[1:] != token[:-1]) | (i[1:] != i[:-1]) | (j[1:] != j[:-1]))])
        n, rank = (place >> 28) & ((1 << 28) - 1), place & ((1 << 28) - 1)
        order = np.lexsort((n, group))
        i, j, block, sid, label, home, n, rank, group = (c[order] for c in (i, j, block, sid, label, home, n, rank, group))
        bits = np.frombuffer(b"".join(rows.column(8).to_pylist()), np.uint64).reshape(len(sid), -1)[order]
        sized = (group << 32) + n
        count = np.searchsorted(sized, (group << 32) + 4 * n // 3, "right") - np.arange(len(n)) - 1
        ends = np.cumsum(count)
        start = 0
        while start < len(n):
            stop = max(start + 1, int(np.searchsorted(ends, (ends[start - 1] if start else 0) + (1 << 18), "right")))
            own = count[start:stop]
            x = np.repeat(np.arange(start, stop), own)
            y = x + 1 + np.arange(len(x)) - np.repeat(np.cumsum(own) - own, own)
            ok = (label[x] != label[y]) & (home[x] != home[y]) & (7 * np.minimum(n[x] - rank[x], n[y] - rank[y]) >= 3 * (n[x] + n[y])) & ((i[x] == j[x]) | (block[x] != block[y]))
            x, y = x[ok], y[ok]
            differing = np.bitwise_count(bits[x] ^ bits[y]).sum(axis=1, dtype=np.int64)
            ok = 7 * differing <= n[x] + n[y]
            x, y, differing = x[ok], y[ok], differing[ok]
            swap = label[x] > label[y]
            x, y = np.where(swap, y, x), np.where(swap, x, y)
            more = np.zeros(len(x), bool)
            if limit and len(x):
                by = np.lexsort((differing, label[y], label[x], group[x]))
                x, y = x[by], y[by]
                new = np.ones(len(x), bool)
                new[1:] = (group[x][1:] != group[x][:-1]) | (label[x][1:] != label[x][:-1]) | (label[y][1:] != label[y][:-1])
                nth = np.arange(len(x)) - np.maximum.accumulate(np.where(new, np.arange(len(x)), 0))
                many = np.bincount(np.cumsum(new) - 1)[np.cumsum(new) - 1] > limit
                x, y, more = x[nth < limit], y[nth < limit], many[nth < limit]
            if len(x):
                yield pa.RecordBatch.from_arrays([pa.array(c) for c in (sid[x], sid[y], more)], ["a", "b", "more"])
            start = stop

    for batch in batches:
        held.append(batch)
        if sum(b.num_rows for b in held) < 1 << 14:
            continue
        rows = pa.Table.from_batches(held).combine_chunks()
        token, i, j = (rows.column(k).to_numpy() for k in range(3))
        last = int(np.argmax((token == token[-1]) & (i == i[-1]) & (j == j[-1])))  # the last group may go on
        if last:
            yield from found(rows.slice(0, last))
        held = rows.slice(last).to_batches()
    if held:
        yield from found(pa.Table.from_batches(held))
    tidy()


def _linked(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        keep = pa.array([_links(np.frombuffer(x.as_buffer(), np.uint64), np.frombuffer(y.as_buffer(), np.uint64)) for x, y in zip(batch.column(2), batch.column(3))], pa.bool_())
        yield pa.RecordBatch.from_arrays([batch.column(0).filter(keep), batch.column(1).filter(keep)], ["a", "b"])
    tidy()


def components(links: DataFrame) -> DataFrame:
    """node, label (the smallest node reachable) of every node of links a, b.

    Each round takes the neighbours' smallest label and then the label of that label, so long chains take few rounds.
    """
    edges = written(links.select(F.col("a").alias("node"), F.col("b").alias("other")).union(links.select("b", "a")).distinct(), "cc-edges")
    rows = written(edges.groupBy("node").agg(F.least(F.first("node"), F.min("other")).alias("label")), "cc")
    while True:
        labels = rows.select("node", "label")
        around = edges.join(labels.withColumnRenamed("node", "other"), "other").groupBy("node").agg(F.min("label").alias("near"))
        step = labels.join(around, "node").select("node", "label", F.least("label", "near").alias("next"))
        far = labels.select(F.col("node").alias("next"), F.col("label").alias("far"))
        rows = written(step.join(far, "next", "left").select("node", F.least("next", "far").alias("label"), F.col("label").alias("old")), "cc", rows)
        if rows.filter(F.col("label") != F.col("old")).isEmpty():
            return written(rows.select("node", "label"), "cc-labels", rows, edges)


def _trees(nodes: DataFrame) -> DataFrame:
    """sid, n, family, home of every set: a leader has a smaller id than the sets it leads, so leaders' leaders end in a family.

    home is the block of the family in which all pairs of its sets are checked.
    """
    found = nodes.select("sid", "n", F.col("leader").alias("family"))
    for _ in range(JUMPS):
        above = found.select(F.col("sid").alias("up"), F.col("family").alias("top"))
        found = written(found.join(above, F.col("family") == F.col("up"), "left").select("sid", "n", F.coalesce("top", "family").alias("family")), "join-trees")
    blocks = F.greatest(F.ceil(F.count(F.lit(1)) / BLOCK_SETS), F.ceil(F.sum("n") / BLOCK_SHINGLES)).cast("int").alias("blocks")
    sizes = found.groupBy("family").agg(blocks)
    block = F.pmod(F.xxhash64("sid"), F.col("blocks")).cast("int")
    return written(found.join(sizes, "family").select("sid", "n", "family", block.alias("block"), F.xxhash64("family", block).alias("home")), "join-homes")


def _block_links_of(arrays: DataFrame) -> DataFrame:
    """Links a, b inside the blocks."""
    rows = arrays.select("family", "block", "sid", "bits", "shingles")
    return rows.repartition("family", "block").sortWithinPartitions("family", "block").mapInArrow(_block_links, "a long, b long")


def _mixed(tiles: DataFrame, labels: DataFrame) -> DataFrame:
    """Rows of the tiles that hold sets of several components and homes, with their component and the number of the tile's last block.

    Components only grow, so a tile that is left out once stays out.
    """
    rows = tiles.join(labels.withColumnRenamed("node", "sid"), "sid", "left").withColumn("label", F.coalesce("label", "sid"))
    several = lambda c: F.min(c) != F.max(c)
    mixed = rows.groupBy("token").agg((several("label") & several("home")).alias("open"), F.floor(F.max("number") / TILE_BLOCK).cast("int").alias("last")).filter("open")
    return rows.join(mixed.select("token", "last"), "token")


def _open_links(tiles: DataFrame, labels: DataFrame, arrays: DataFrame, limit: int | None) -> tuple[DataFrame, DataFrame]:
    """Links a, b between components that meet in a tile, and pairs of components (as pairs of sets) with more pairs than the limit."""
    block = F.floor(F.col("number") / TILE_BLOCK).cast("int")
    around = F.transform(F.sequence(F.lit(0), F.col("last")), lambda k: F.struct(F.least(k, F.col("block")).alias("i"), F.greatest(k, F.col("block")).alias("j")))
    rows = _mixed(tiles, labels).withColumn("block", block).join(arrays.select("sid", "bits"), "sid")
    rows = rows.select("token", F.explode(around).alias("of"), "block", "sid", "label", "place", "home", "bits").select("token", "of.i", "of.j", "block", "sid", "label", "place", "home", "bits")
    pairs = rows.repartition("token", "i", "j").sortWithinPartitions("token", "i", "j").mapInArrow(lambda b: _tile_pairs(b, limit), "a long, b long, more boolean")
    pairs = written(pairs.groupBy("a", "b").agg(F.max("more").alias("more")), "join-pairs")
    of = lambda end, name: arrays.select(F.col("sid").alias(end), F.col("shingles").alias(name))
    links = written(pairs.join(of("a", "x"), "a").join(of("b", "y"), "b").select("a", "b", "x", "y").mapInArrow(_linked, "a long, b long"), "join-links")
    return links, pairs


def _labelled(docs: DataFrame, id_col: str, text_col: str) -> DataFrame:
    """doc_id, text_hash, n, sid, label of every row: label is a set of its component, null without shingles."""
    from pyspark.sql.pandas.types import to_arrow_type

    spark = docs.sparkSession
    source = docs.select(F.col(text_col).cast("string").alias("text"))
    rows = docs.select(F.col(id_col).alias("doc_id"), F.xxhash64(F.col(text_col).cast("string")).alias("text_hash"), F.col(text_col).cast("string").alias("text"))
    kind = rows.schema["doc_id"].dataType
    id_type = to_arrow_type(kind)
    sets = written(rows.mapInArrow(lambda b: _sets(b, id_type), SET_SCHEMA.format(id_type=kind.simpleString())), "join-sets")
    levels = spark.sparkContext.broadcast(rarity(sets))
    sent = source.mapInArrow(lambda b: _prefixes(b, levels), "token long, sid long, place long")
    band = F.shiftright("place", 56)
    tiles = written(sent.repartition("token").sortWithinPartitions("token", band, "sid").mapInArrow(_tiles, "token long, sid long, place long, leader long, number long"), "join-tiles")
    levels.destroy()
    # a set's tiles by leader: linked sets meet in 1 + least size // MEET tiles or more, and that size is 3/4 of either's at least
    size, enough = F.shiftright("place", 28).bitwiseAND(F.lit((1 << 28) - 1)), F.col("met") >= 1 + F.floor(F.ceil(0.75 * F.col("n")) / MEET)
    votes = tiles.groupBy("sid", "leader").agg(F.count(F.lit(1)).alias("votes"), F.first(size).alias("n"))
    best = F.max_by("leader", F.struct(F.col("leader") != F.col("sid"), "votes", "leader")).alias("leader")
    nodes = votes.groupBy("sid").agg(F.sum("votes").alias("met"), F.first("n").alias("n"), best).filter(enough)
    nodes = written(nodes.select("sid", "n", "leader"), "join-nodes")
    wanted = spark.sparkContext.broadcast(bit_filter(nodes.select("sid")))
    homes = _trees(nodes)
    arrays = source.mapInArrow(lambda b: _arrays(b, wanted), "sid long, bits binary, shingles binary").join(homes.select("sid", "family", "block"), "sid")
    arrays = written(arrays.dropDuplicates(["sid"]), "join-arrays")
    wanted.destroy()
    labels = components(_block_links_of(arrays))
    settle(spark)
    slim = tiles.join(homes.select("sid", "home"), "sid").select("token", "sid", "place", "number", "home")
    mixed = written(_mixed(slim, labels).select("token", "sid", "place", "number", "home"), "join-mixed")
    # the tiles that two linked sets of different components and homes share are all among these
    able = mixed.groupBy("sid").agg(F.count(F.lit(1)).alias("met"), F.first(size).alias("n")).filter(enough).select("sid")
    mixed = written(mixed.join(able, "sid", "left_semi"), "join-open", mixed)
    discard(tiles, nodes, homes)
    links, pairs = _open_links(mixed, labels, arrays, FIRST)
    labels = _joined(labels, links)
    of = lambda end: labels.select(F.col("node").alias(end), F.col("label").alias(f"{end}_label"))
    left = pairs.filter("more").join(of("a"), "a", "left").join(of("b"), "b", "left").filter(F.coalesce("a_label", "a") != F.coalesce("b_label", "b"))
    if not left.isEmpty():
        discard(links, pairs)
        links, pairs = _open_links(mixed, labels, arrays, None)
        labels = _joined(labels, links)
    discard(links, pairs, mixed, arrays)
    settle(spark)
    documents = sets.filter("chunk is null").select("doc_id", "text_hash", "n", "sid")
    return documents.join(labels.withColumnRenamed("node", "sid"), "sid", "left").withColumn("label", F.coalesce("label", "sid"))


def join(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id of every document: the smallest id reachable by links, itself included.

    Null, empty and blank texts have no shingles and are linked with nothing. Repeated rows and equal texts link; an
    empty table gives no rows. A null id is never the smallest unless all of its component are null. Other columns are
    not read.
    """
    rows = written(_labelled(docs, id_col, text_col).select("doc_id", "n", "label"), "join-labelled")
    least = rows.filter("label is not null").groupBy("label").agg(F.min("doc_id").alias("component_id"))
    out = rows.join(least, "label", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("label").isNull(), F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def _joined(labels: DataFrame, links: DataFrame) -> DataFrame:
    """labels (node, label) after more links: components of the components that the links join."""
    if links.isEmpty():
        return labels
    of = lambda end: labels.select(F.col("node").alias(end), F.col("label").alias(f"{end}_label"))
    between = links.join(of("a"), "a", "left").join(of("b"), "b", "left").select(F.coalesce("a_label", "a").alias("a"), F.coalesce("b_label", "b").alias("b"))
    found = components(between.filter("a <> b").distinct())
    step = found.select(F.col("node").alias("label"), F.col("label").alias("next"))
    known = labels.union(links.select("a", "a")).union(links.select("b", "b")).groupBy("node").agg(F.min(F.struct((F.col("node") == F.col("label")).alias("new"), "label")).alias("x"))
    known = known.select("node", "x.label")
    return written(known.join(step, "label", "left").select("node", F.coalesce("next", "label").alias("label")), "join-labels", found)


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """docs with one row of each component: the one of smallest id (null last; equal ids by a hash of the text).

    Rows are told apart by id and text, so unlike texts that share an id are judged apart. Texts without words all stay.
    """
    rows = written(_labelled(docs, id_col, text_col).filter("label is not null").select("doc_id", "text_hash", "label"), "join-labelled")
    first = rows.groupBy("label").agg(F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "text_hash")).alias("f")).select("f.doc_id", "f.text_hash")
    first = first.withColumnsRenamed({"doc_id": "__join_id", "text_hash": "__join_hash"})
    same = F.col("doc_id").eqNullSafe(F.col("__join_id")) & (F.col("text_hash") == F.col("__join_hash"))
    kept = written(rows.join(first, same).groupBy("__join_id", "__join_hash").agg(F.count(F.lit(1)).alias("__join_rows")), "join-kept")
    text = F.col(text_col).cast("string")
    wordless = ~F.coalesce(text.rlike(r"[^\x20\x09-\x0D]"), F.lit(False))
    held = docs.filter(~wordless).join(kept, F.col(id_col).eqNullSafe(F.col("__join_id")) & (F.xxhash64(text) == F.col("__join_hash")))
    out = held.filter("__join_rows = 1").select(docs.columns).union(docs.filter(wordless))
    if kept.filter("__join_rows > 1").isEmpty():
        return out
    return out.union(held.filter("__join_rows > 1").dropDuplicates(["__join_id", "__join_hash"]).select(docs.columns))
