"""Token ids in Simple-8b: 64-bit words of a 4-bit selector and up to 60 bits of equally wide ids.

File format. A shard is one Parquet file of blocks in ascending document order. A block holds whole documents:
  shard, block     place of the block
  doc_ids, lengths documents of the block, and how many ids each has
  n_ids            ids of the block
  offsets          for every RUN ids, where their words begin (little-endian unsigned 32-bit), so that runs are decoded
                   apart or all at once
  words            little-endian 64-bit words: the selector in the low 4 bits, ids above it from the low end
Selector 0 is an escape: the next word is one raw 64-bit id. A run's last word may be padded with zeros. Runs do not
share words.
"""

from __future__ import annotations

import json
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from runloom.llm.common import buffers, pieces, texts, tidy, work_dir
from runloom.llm.textnum import mix

#: Ids in a word and their bits, by selector; selector 0 is the escape.
COUNT = np.array([1, 60, 30, 20, 15, 12, 10, 8, 7, 6, 5, 4, 3, 2, 1], np.int64)
WIDTH = np.array([64, 1, 2, 3, 4, 5, 6, 7, 8, 10, 12, 15, 20, 30, 60], np.int64)
#: Ids that are coded and decoded as one unit; many runs advance together.
RUN = 512
#: A block is closed after the document that reaches this many ids.
BLOCK_IDS = 1 << 20
END_ID = 2
#: Bytes of text encoded at once.
ENCODE_BYTES = 4 << 20
#: Most chunks that a worker remembers, beside those of the texts at hand; beyond them it starts anew.
MEMORY = 1 << 19
#: Longest chunk (in bytes) that is remembered: three words of eight bytes, the last of which holds the length.
SHORT = 23

def encode(ids: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Words (uint64) and run offsets (uint32) of unsigned ids; all runs take a step at a time."""
    ids = np.ascontiguousarray(ids, np.uint64)
    n = len(ids)
    runs = -(-n // RUN)
    if not n:
        return np.zeros(0, np.uint64), np.zeros(0, np.uint32)
    grid = np.zeros(runs * RUN + 60, np.uint64)
    grid[:n] = ids
    last = np.minimum((np.arange(runs) + 1) * RUN, n)
    # narrowest width class of each id, then the widest class among the next COUNT ids: a place may pack by selector s if it is <= s
    cls = np.searchsorted(WIDTH[1:], np.maximum(1, _bits(grid)), "left") + 1
    cls = np.where(grid >> np.uint64(60) > 0, 15, cls).astype(np.int8)
    best = np.full(runs * RUN, 15, np.int8)
    reach = cls[: runs * RUN].copy()  # highest class of the next `width` ids, grown from short windows to long
    width = 1
    for s in range(14, 0, -1):
        count = int(COUNT[s])
        while width < count:
            step = min(width, count - width)
            longer = np.full_like(reach, 0)
            longer[: len(reach) - step] = reach[step:]
            reach = np.maximum(reach, longer)
            width += step
        best[reach <= s] = s
    at, out, place = np.arange(runs) * RUN, [], []
    active = np.arange(runs)
    while len(active):
        pos = at[active]
        s = best[pos].astype(np.int64)
        room = last[active] - pos
        s_count = np.where(s == 15, 1, COUNT[np.minimum(s, 14)])
        word = np.zeros(len(active), np.uint64)
        raw = s == 15
        for c in np.unique(s[~raw]):
            sel = np.flatnonzero(s == c)
            count, bits = int(COUNT[c]), np.uint64(WIDTH[c])
            value = np.full(len(sel), np.uint64(c))
            for j in range(min(count, int(room[sel].max()))):
                x = np.where(j < room[sel], grid[pos[sel] + j], np.uint64(0))
                value |= x << (np.uint64(4) + bits * np.uint64(j))
            word[sel] = value
        out.append(word)
        place.append(active)
        if raw.any():
            out.append(grid[pos[raw]])
            place.append(active[raw])
        at[active] += np.minimum(s_count, room)
        active = active[at[active] < last[active]]
    owner = np.concatenate(place)
    order = np.argsort(owner, kind="stable")
    return np.concatenate(out)[order], np.searchsorted(owner[order], np.arange(runs)).astype(np.uint32)


def _bits(x: np.ndarray) -> np.ndarray:
    """Bit lengths of unsigned 64-bit integers."""
    high, low = (x >> np.uint64(32)).astype(np.float64), (x & np.uint64((1 << 32) - 1)).astype(np.float64)
    return np.where(high > 0, np.frexp(high)[1] + 32, np.frexp(low)[1])


def decode(words: np.ndarray, offsets: np.ndarray, n_ids: int) -> np.ndarray:
    """All ids of a block. Selectors are read at once unless the block has escapes, whose raw words are found run by run."""
    if not n_ids:
        return np.zeros(0, np.uint64)
    selector = (words & np.uint64(15)).astype(np.int64)
    is_raw = np.zeros(len(words), bool)
    if (selector == 0).any():
        for k in np.flatnonzero(selector == 0):  # left to right: a raw word may look like an escape
            if not is_raw[k]:
                is_raw[k + 1] = True
    head = np.flatnonzero(~is_raw)
    s = selector[head]
    count = COUNT[s]
    run = np.searchsorted(offsets, head, "right") - 1
    before = np.cumsum(count) - count
    first = np.searchsorted(run, np.arange(len(offsets)))
    start = run * RUN + before - before[first][run]
    out = np.zeros(len(offsets) * RUN + 60, np.uint64)
    for c in np.unique(s):
        sel = np.flatnonzero(s == c)
        if c == 0:
            out[start[sel]] = words[head[sel] + 1]
            continue
        bits, end = np.uint64(WIDTH[c]), (run[sel] + 1) * RUN
        mask = np.uint64((1 << int(WIDTH[c])) - 1)
        for j in range(int(COUNT[c])):
            ok = start[sel] + j < end
            out[start[sel][ok] + j] = (words[head[sel][ok]] >> (np.uint64(4) + bits * np.uint64(j))) & mask
    return out[:n_ids]


def _ascii(*ranges: tuple[int, int]) -> np.ndarray:
    out = np.zeros(256, bool)
    for low, high in ranges:
        out[low : high + 1] = True
    return out


_SPACE, _ALNUM, _PUNCTUATION = _ascii((9, 13), (32, 32)), _ascii((48, 57), (65, 90), (97, 122)), _ascii((33, 47), (58, 64), (91, 96), (123, 126))
_MASK = np.array([(1 << 8 * k) - 1 for k in range(9)], np.uint64)


def _after_wide_space(buf: np.ndarray, at: np.ndarray) -> np.ndarray:
    """True where the character before a place is white space of several bytes (Unicode's White_Space, fixed values)."""
    x, y, z = (np.where(at >= k, buf[np.maximum(at - k, 0)], 0) for k in (3, 2, 1))
    general = (x == 0xE2) & (((y == 0x80) & ((z <= 0x8A) | np.isin(z, (0xA8, 0xA9, 0xAF)))) | ((y == 0x81) & (z == 0x9F)))
    return general | ((y == 0xC2) & np.isin(z, (0x85, 0xA0))) | ((x == 0xE1) & (y == 0x9A) & (z == 0x80)) | ((x == 0xE3) & (y == 0x80) & (z == 0x80))


def _grown(x: np.ndarray, size: int) -> np.ndarray:
    """x with room for size rows at least."""
    if size <= len(x):
        return x
    out = np.empty((max(size, 2 * len(x)), *x.shape[1:]), x.dtype)
    out[: len(x)] = x
    return out


class ChunkMemory:
    """A hash table of short chunks, by their bytes, and their ids in one pool."""

    def __init__(self) -> None:
        self.slots, self.n, self.n_ids = np.full(4 * MEMORY + 4, -1, np.int32), 0, 0
        self.keys, self.place, self.count, self.pool = np.zeros((0, 3), np.uint64), np.zeros(0, np.int64), np.zeros(0, np.int64), np.zeros(0, np.uint32)

    def find(self, keys: np.ndarray, hashes: np.ndarray) -> np.ndarray:
        """Number of each chunk, -1 where it is unknown."""
        out = np.full(len(keys), -1, np.int64)
        if not self.n:
            return out
        pending, slot = np.arange(len(keys)), (hashes % np.uint64(len(self.slots))).astype(np.int64)
        while len(pending):
            entry = self.slots[slot]
            known, asked = self.keys[entry], keys[pending]
            same = (entry >= 0) & (known[:, 0] == asked[:, 0]) & (known[:, 1] == asked[:, 1]) & (known[:, 2] == asked[:, 2])
            out[pending[same]] = entry[same]
            go = (entry >= 0) & ~same
            pending, slot = pending[go], (slot[go] + 1) % len(self.slots)
        return out

    def add(self, count: np.ndarray, ids: np.ndarray, keys: np.ndarray) -> None:
        n, n_ids = self.n + len(count), self.n_ids + len(ids)
        self.keys, self.place, self.count, self.pool = _grown(self.keys, n), _grown(self.place, n), _grown(self.count, n), _grown(self.pool, n_ids)
        self.place[self.n : n] = self.n_ids + np.cumsum(count) - count
        self.count[self.n : n], self.keys[self.n : n], self.pool[self.n_ids : n_ids] = count, keys, ids
        self.n, self.n_ids = n, n_ids

    def keep(self, n: int) -> None:
        if n < self.n:
            self.n, self.n_ids = n, int(self.place[n])

    def index(self, entries: np.ndarray, hashes: np.ndarray) -> None:
        slot = (hashes % np.uint64(len(self.slots))).astype(np.int64)
        while len(entries):
            free = self.slots[slot] < 0
            self.slots[slot[free]] = entries[free]  # of several the last one stands
            go = self.slots[slot] != entries
            entries, slot = entries[go], (slot[go] + 1) % len(self.slots)


class ChunkEncoder:
    """Ids of whole texts by the tokenizers library.

    A byte-level tokenizer's splitter ends a piece before white space that follows other characters, and between an ASCII
    letter or digit and ASCII punctuation. Texts are cut there, and the tokenizer sees each different chunk once. A tokenizer
    that splits in other ways encodes whole texts.
    """

    def __init__(self, path: str) -> None:
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        size = self.tokenizer.get_vocab_size(True)
        added = self.tokenizer.get_added_tokens_decoder()
        # every other token is spelled with one character per byte
        self.n_bytes = np.array([len(added[i].content.encode()) if i in added else len(self.tokenizer.id_to_token(i) or "") for i in range(size)], np.int64)
        form = json.loads(self.tokenizer.to_str())
        splitter = form["pre_tokenizer"] or {}
        odd = any(t.lstrip or t.rstrip or t.single_word or any(c.isspace() for c in t.content) for t in added.values())
        self.chunked = splitter.get("type") == "ByteLevel" and splitter.get("use_regex") and not splitter.get("add_prefix_space") and not form["normalizer"] and not odd
        self.punctuation = _PUNCTUATION.copy()  # but for what stands inside an added token
        self.punctuation[[b for t in added.values() for b in t.content[1:].encode()]] = False
        self.memory = ChunkMemory()

    def _starts(self, buf: np.ndarray) -> np.ndarray:
        """True where a chunk may begin, as far as the bytes before tell."""
        cut = np.zeros(len(buf), bool)
        space = _SPACE[buf]
        cut[1:] = (space[1:] & ~space[:-1]) | (self.punctuation[buf[1:]] & _ALNUM[buf[:-1]])
        at = np.flatnonzero(cut[1:] & (buf[:-1] >= 0x80)) + 1
        cut[at[_after_wide_space(buf, at)]] = False
        return cut

    def _learn(self, buf: np.ndarray, start: np.ndarray, length: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids and their numbers of the chunks of buf at start. Those that start with white space and end with other characters are encoded as one text and cut by byte lengths."""
        end = start + length
        spaced = _SPACE[buf[start]] & ~_SPACE[buf[end - 1]] & ~((buf[end - 1] >= 0x80) & _after_wide_space(buf, end))
        out, count = [], np.zeros(len(start), np.int64)
        at = np.flatnonzero(spaced)
        for k in range(0, len(at), 8192):
            part = at[k : k + 8192]
            ends = np.cumsum(length[part])
            text = buf[np.repeat(start[part] - (ends - length[part]), length[part]) + np.arange(ends[-1])].tobytes().decode()
            ids = np.array(self.tokenizer.encode(text, add_special_tokens=False).ids, np.uint32)
            out.append(ids)
            count[part] = np.diff(np.searchsorted(np.cumsum(self.n_bytes[ids]), ends) + 1, prepend=0)
        rest = np.flatnonzero(~spaced)
        found = self.tokenizer.encode_batch([buf[a:b].tobytes().decode() for a, b in zip(start[rest], end[rest])], add_special_tokens=False)
        count[rest] = [len(e.ids) for e in found]
        out += [np.array(e.ids, np.uint32) for e in found]
        ids = np.concatenate([np.zeros(0, np.uint32), *out])
        # from the order of encoding back to that of the chunks
        order = np.concatenate([at, rest])
        place = np.empty(len(start), np.int64)
        place[order] = np.cumsum(count[order]) - count[order]
        return ids[np.repeat(place - (np.cumsum(count) - count), count) + np.arange(len(ids))], count

    def _window(self, buf: np.ndarray, start: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of the chunks that begin at start, and how many each has."""
        memory = self.memory
        if memory.n > MEMORY:
            memory = self.memory = ChunkMemory()
        length = np.diff(np.append(start, len(buf)))
        padded = np.concatenate([buf, np.zeros(24, np.uint8)])
        word = np.ndarray((len(buf) + 16,), np.uint64, padded, strides=(1,))  # eight bytes from every place on
        keys = np.empty((len(start), 3), np.uint64)
        for k in range(3):
            keys[:, k] = word[start + 8 * k] & _MASK[np.clip(length - 8 * k, 0, 8)]
        short = length <= SHORT
        keys[short, 2] |= length[short].astype(np.uint64) << np.uint64(56)
        hashes = mix(mix(mix(keys[:, 0]) ^ keys[:, 1]) + keys[:, 2])
        entry = np.full(len(start), -1, np.int64)
        at = np.flatnonzero(short)
        entry[at] = memory.find(keys[at], hashes[at])
        new = at[entry[at] < 0]
        _, first, inverse = np.unique(hashes[new], return_index=True, return_inverse=True)
        same = (keys[new] == keys[new[first[inverse]]]).all(axis=1)  # others share a hash: each for itself, as long chunks
        once, other = new[first], np.concatenate([np.flatnonzero(~short), new[~same]])
        number: dict[bytes, int] = {}
        places = []  # of the different long chunks
        for k in other.tolist():
            chunk = buf[start[k] : start[k] + length[k]].tobytes()
            if chunk not in number:
                number[chunk] = len(number)
                places.append(k)
            entry[k] = memory.n + len(once) + number[chunk]
        entry[new[same]] = memory.n + inverse[same]
        asked = np.concatenate([once, np.array(places, np.int64)])
        ids, count = self._learn(buf, start[asked], length[asked])
        known = memory.n
        memory.add(count, ids, np.concatenate([keys[once], np.zeros((len(places), 3), np.uint64)]))
        counts = memory.count[entry]
        ids = memory.pool[np.repeat(memory.place[entry] - (np.cumsum(counts) - counts), counts) + np.arange(counts.sum())]
        kept = min(known + len(once), len(memory.slots) // 2)  # neither long chunks nor those beyond half of the table stay
        memory.keep(kept)
        memory.index(np.arange(known, kept, dtype=np.int32), hashes[once[: kept - known]])
        return ids, counts

    def encode(self, column: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of a null-free column's texts, one after the other, and how many each has."""
        if not self.chunked:
            found = [np.array(e.ids, np.uint32) for e in self.tokenizer.encode_batch(column.to_pylist(), add_special_tokens=False)]
            return np.concatenate([np.zeros(0, np.uint32), *found]), np.array([len(x) for x in found], np.int64)
        buf, offs = buffers(column)
        out, lo = [np.zeros(0, np.uint32)], 0
        ends, totals, before = [], [], 0  # for each chunk: where it ends, ids up to there
        while lo < len(buf):
            size = ENCODE_BYTES
            while True:
                part = buf[lo : lo + size]
                cut = self._starts(part)
                cut[0] = True
                borders = offs[(offs > lo) & (offs < lo + len(part))] - lo
                cut[borders] = True
                start = np.flatnonzero(cut)
                if lo + len(part) == len(buf) or len(start) > 1:
                    break
                size *= 2  # no cut in here
            if lo + len(part) < len(buf):
                part, start = part[: start[-1]], start[:-1]
            ids, counts = self._window(part, start)
            out.append(ids)
            ends.append(np.append(start[1:], len(part)) + lo)
            totals.append(before + np.cumsum(counts))
            before += len(ids)
            lo += len(part)
        ends, totals = np.concatenate([[0], *ends]), np.concatenate([[0], *totals])
        return np.concatenate(out), np.diff(totals[np.searchsorted(ends, offs)])


_encoders: dict[str, ChunkEncoder] = {}
BLOCK_SCHEMA = "shard long, block int, doc_ids array<{id_type}>, lengths array<long>, n_ids long, offsets binary, words binary"


def _blocks(batches: Iterator[pa.RecordBatch], vocabulary: str, id_type: pa.DataType) -> Iterator[pa.RecordBatch]:
    encoder = _encoders.get(vocabulary) or _encoders.setdefault(vocabulary, ChunkEncoder(vocabulary))
    shard, block = TaskContext.get().partitionId(), 0
    ids, lengths, parts, size = [], [], [], 0
    types = [pa.int64(), pa.int32(), pa.list_(id_type), pa.list_(pa.int64()), pa.int64(), pa.binary(), pa.binary()]

    def closed() -> pa.RecordBatch:
        values = np.concatenate(parts)
        words, offsets = encode(values)
        row = [shard, block, ids, lengths, len(values), offsets.tobytes(), words.tobytes()]
        return pa.RecordBatch.from_arrays([pa.array([v], t) for v, t in zip(row, types)], ["shard", "block", "doc_ids", "lengths", "n_ids", "offsets", "words"])

    for batch in batches:
        column, names = texts(batch.column(1)), batch.column(0).to_pylist()
        for lo, hi in pieces(column, ENCODE_BYTES):
            found, counts = encoder.encode(column.slice(lo, hi - lo))
            ends = np.cumsum(counts)
            found, counts = np.insert(found, ends, np.uint32(END_ID)), counts + 1
            ends = np.cumsum(counts)
            start, at = 0, 0  # documents and ids that are in a block
            while start < hi - lo:
                stop = min(hi - lo, int(np.searchsorted(ends, at + BLOCK_IDS - size)) + 1)
                ids.extend(names[lo + start : lo + stop])
                lengths.extend(counts[start:stop].tolist())
                parts.append(found[at : ends[stop - 1]])
                size += len(parts[-1])
                start, at = stop, ends[stop - 1]
                if size >= BLOCK_IDS:
                    yield closed()
                    ids, lengths, parts, size, block = [], [], [], 0, block + 1
    if ids:
        yield closed()
    tidy()


def write(docs: DataFrame, path: str, vocabulary: str, id_col: str = "doc_id", text_col: str = "text") -> None:
    """Encodes docs in ascending order of id (null first; equal ids by text) and writes shards below path.

    Null text counts as empty: it has the end id alone. An empty table writes no block.
    """
    from pyspark.sql.pandas.types import to_arrow_type

    source = docs.select(F.col(id_col).alias("doc_id"), F.coalesce(F.col(text_col).cast("string"), F.lit("")).alias("text"))
    kind = source.schema["doc_id"].dataType
    id_type = to_arrow_type(kind)
    order = ["doc_id", F.xxhash64("text")]
    ranged = source.repartitionByRange(*order).sortWithinPartitions(*order, "text")
    ranged.mapInArrow(lambda b: _blocks(b, vocabulary, id_type), BLOCK_SCHEMA.format(id_type=kind.simpleString())).write.parquet(path)


def _documents(batches: Iterator[pa.RecordBatch], with_ids: bool) -> Iterator[pa.RecordBatch]:
    for batch in batches:
        for r in range(batch.num_rows):
            shard, block, n_ids = (batch.column(k)[r].as_py() for k in (0, 1, 4))
            words = np.frombuffer(batch.column(6)[r].as_buffer(), np.uint64)
            offsets = np.frombuffer(batch.column(5)[r].as_buffer(), np.uint32)
            ids = decode(words, offsets, n_ids).astype(np.uint32)
            lengths = np.array(batch.column(3)[r].as_py(), np.int64)
            ends = np.cumsum(lengths)
            data = ids.tobytes()
            crc = [zlib.crc32(data[4 * (e - n) : 4 * e]) for e, n in zip(ends.tolist(), lengths.tolist())]
            count = len(lengths)
            cols = [pa.array([shard] * count, pa.int64()), pa.array([block] * count, pa.int32()), batch.column(2)[r].values, pa.array(ends - lengths), pa.array(lengths), pa.array(crc, pa.int64())]
            names = ["shard", "block", "doc_id", "in_block", "n_tokens", "ids_crc32"]
            if with_ids:
                cols.append(pa.array([ids[e - n : e].tolist() for e, n in zip(ends, lengths)], pa.list_(pa.int64())))
                names.append("ids")
            yield pa.RecordBatch.from_arrays(cols, names)


def read(blocks: DataFrame, with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids) of every document in the shards.

    start comes from sums over blocks: running sums inside a shard, and over the shards' totals (a row each).
    """
    kind = blocks.schema["doc_ids"].dataType.elementType.simpleString()
    ddl = f"shard long, block int, doc_id {kind}, in_block long, n_tokens long, ids_crc32 long" + ", ids array<long>" * with_ids
    documents = blocks.select("shard", "block", "doc_ids", "lengths", "n_ids", "offsets", "words").mapInArrow(lambda b: _documents(b, with_ids), ddl)
    before = lambda *by: Window.partitionBy(*by[:-1]).orderBy(by[-1]).rowsBetween(Window.unboundedPreceding, -1)
    sizes = blocks.select("shard", "block", "n_ids")
    shards = sizes.groupBy("shard").agg(F.sum("n_ids").alias("n")).select("shard", F.coalesce(F.sum("n").over(before("shard")), F.lit(0)).alias("shard_start"))
    base = sizes.withColumn("in_shard", F.coalesce(F.sum("n_ids").over(before("shard", "block")), F.lit(0))).join(shards, "shard")
    start = (F.col("shard_start") + F.col("in_shard") + F.col("in_block")).cast("long").alias("start")
    return documents.join(base.select("shard", "block", "in_shard", "shard_start"), ["shard", "block"]).select("doc_id", start, "n_tokens", "ids_crc32", *["ids"] * with_ids)


def encode_table(docs: DataFrame, vocabulary: str, with_ids: bool = False) -> DataFrame:
    """write() to the shared folder, then read()."""
    spark = docs.sparkSession
    path = work_dir(spark, "tokens")
    write(docs, path, vocabulary)
    return read(spark.read.parquet(path), with_ids)
