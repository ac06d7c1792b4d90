"""Token-id files: ids bit-packed at the least width for the vocabulary, in blocks with offsets.

File format. A token file is a Parquet table of blocks sorted by (shard, block). Each block holds
  shard int, block long     position: ascending (shard, block) is ascending document order
  bits int                  width of an id, the fewest bits that hold every id of the vocabulary
  n_ids long                ids in the block
  payload binary            the ids, little-endian bit order, id i at bits [i * bits, (i + 1) * bits)
  doc_ids array<long>       the documents of this block, in order
  lengths array<long>       ids of each of them
A document lies in one block, and a block is closed once it holds `block_ids` ids, so a block is at most that
and one document long. Any id range is read by unpacking only the blocks, and in them the bytes, that hold it. Parquet is the container since Spark writes no other binary files to any store.

Null and empty texts encode to the end id alone. Texts of any length are encoded whole. Repeated rows and repeated doc_ids stay
separate documents, ordered by a hash of the text and the text; a null doc_id sorts first. The ranges are cut by doc_id, hash and
row number, so rows of one doc_id, or one row repeated without end, are dealt to many tasks. An empty table gives an empty
file. Columns other than doc_id, text and those of `order` are not read, whatever their names.
"""
from __future__ import annotations

import json
import os
import zlib
from array import array

import numpy as np
import pyarrow as pa
from pyspark import TaskContext
from pyspark.sql import DataFrame, Window, functions as F

from .common import lean, small_batches, written

BLOCK_IDS = 1 << 20
FLUSH_CHARS = 1 << 19
BLOCKS = "shard int, block long, bits int, n_ids long, payload binary, doc_ids array<long>, lengths array<long>"
ARROW_BLOCKS = pa.schema([("shard", pa.int32()), ("block", pa.int64()), ("bits", pa.int32()), ("n_ids", pa.int64()), ("payload", pa.binary()), ("doc_ids", pa.list_(pa.int64())), ("lengths", pa.list_(pa.int64()))])
_encoders: dict = {}


def id_bits(vocab_size: int) -> int:
    return max(1, int(vocab_size - 1).bit_length())


def pack(ids: np.ndarray, bits: int) -> bytes:
    """Ids to `bits` bits each, in order, little end first."""
    if bits in (8, 16, 32):
        return ids.astype(f"<u{bits // 8}").tobytes()
    planes = (ids.astype(np.uint64)[:, None] >> np.arange(bits, dtype=np.uint64)).astype(np.uint8) & 1
    return np.packbits(planes.reshape(-1), bitorder="little").tobytes()


def unpack(payload: bytes, bits: int, n: int, start: int = 0) -> np.ndarray:
    """`n` ids from id number `start` on; reads only the bytes that hold them."""
    if bits in (8, 16, 32):
        return np.frombuffer(payload, f"<u{bits // 8}", n, start * bits // 8).astype(np.uint32)
    first = start * bits
    raw = np.frombuffer(payload, np.uint8)[first // 8 : (first + n * bits + 7) // 8]
    planes = np.unpackbits(raw, bitorder="little")[first % 8 : first % 8 + n * bits].reshape(n, bits)
    return (planes.astype(np.uint32) << np.arange(bits, dtype=np.uint32)).sum(axis=1, dtype=np.uint32)


class Pieces:
    """A store of pieces' ids that numpy searches for many pieces at once: open addressing on a hash of the bytes.

    It takes pieces of up to WIDE bytes, held whole as three words and a size. A hit agrees in all of them, so it is the same piece.
    """

    SLOTS = 21
    WIDE = 24

    def __init__(self, most: int):
        self.most, self.n = most, 0
        self.keys = np.zeros(1 << self.SLOTS, np.uint64)
        self.entry = np.zeros(1 << self.SLOTS, np.int32)
        self.whole, self.sizes = np.zeros((most + 1, 3), np.uint64), np.zeros(most + 1, np.int32)
        self.at, self.count = np.zeros(most + 1, np.int64), np.zeros(most + 1, np.int64)
        self.pool, self.used = np.zeros(1 << 20, "<u4"), 0

    def find(self, h: np.ndarray, whole: np.ndarray, size: np.ndarray) -> np.ndarray:
        """Entry of each piece, 0 if unknown."""
        out = np.zeros(len(h), np.int32)
        mask = np.int64((1 << self.SLOTS) - 1)
        slot = (h >> np.uint64(64 - self.SLOTS)).astype(np.int64)
        todo = np.arange(len(h))
        while len(todo):
            k = self.keys[slot]
            same = k == h[todo]
            out[todo[same]] = self.entry[slot[same]]
            on = ~same & (k != 0)
            todo, slot = todo[on], slot[on] + 1 & mask
        wrong = (self.sizes[out] != size) | (self.whole[out] != whole).any(axis=1)
        out[wrong] = 0
        return out

    def add(self, h: int, whole: np.ndarray, size: int, ids: np.ndarray) -> None:
        """Of two pieces with equal hash the first is kept; the other stays unknown and is encoded each time."""
        if self.n >= self.most:
            return
        slot = h >> (64 - self.SLOTS)
        while self.keys[slot] and self.keys[slot] != h:
            slot = slot + 1 & (1 << self.SLOTS) - 1
        if self.keys[slot]:
            return
        self.n += 1
        if self.used + len(ids) > len(self.pool):
            self.pool = np.concatenate([self.pool, np.zeros(len(self.pool) + len(ids), "<u4")])
        self.pool[self.used : self.used + len(ids)] = ids
        self.keys[slot], self.entry[slot] = h, self.n
        self.whole[self.n], self.sizes[self.n], self.at[self.n], self.count[self.n] = whole, size, self.used, len(ids)
        self.used += len(ids)


class Encoder:
    """Encodes texts with a `tokenizers` file, which meets each piece once while there is room, and once a batch beyond that.

    Byte-level BPE never merges across the pieces of its splitting pattern, so the ids of a text are those of its
    pieces joined. Texts of letters (Latin, Cyrillic), digits and ASCII signs with single white space between are cut
    by numpy, many texts at once: there a piece begins where the kind of character changes, and a space goes with what
    follows it. All other texts are cut by the pattern itself. Texts that hold an added token of the file, and all texts
    where the file is no plain byte-level BPE, go whole to the library, which treats them as it does by default.
    """

    KEEP, KEEP_ODD, JOINED = 1_000_000, 60_000, 300

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        import regex
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_file(path)
        self.tok = Tokenizer.from_file(path)
        self.tok.encode_special_tokens = True  # pieces hold no added token
        self.vocab_size = self.tok.get_vocab_size()
        self.added = sorted(t.content for t in self.library.get_added_tokens_decoder().values())
        with open(path, encoding="utf-8") as f:
            made = json.load(f)
        before = made.get("pre_tokenizer") or {}
        self.plain = not made.get("normalizer") and made["model"].get("type") == "BPE" and before.get("type") == "ByteLevel" and not before.get("add_prefix_space") and before.get("use_regex", True)
        # fixed value: the splitting pattern of byte-level BPE
        self.split = regex.compile(r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+").findall
        self.odd: dict[str, bytes] = {}
        self.store = Pieces(self.KEEP)

    # kinds of bytes: 0 letter, 1 digit, 2 sign, 3 space, 4 other white space, 5 left to the pattern
    KIND = np.full(256, 2, np.uint8)
    KIND[:32], KIND[127], KIND[39] = 5, 5, 5
    KIND[[9, 10, 11, 12, 13]], KIND[32], KIND[48:58], KIND[65:91], KIND[97:123] = 4, 3, 1, 0, 0
    KIND[128:192] = 0
    KIND[192:] = 5
    KIND[[0xC3, 0xC4, 0xC5, 0xC6, 0xC7, 0xC8, 0xD0, 0xD1]] = 0

    def _encode(self, new: list[str]) -> dict[str, bytes]:
        """Ids of each piece. A piece that begins with a space and ends in none stands alone in any text, so many of them are
        encoded as one and told apart by the numbers of their words."""
        alone, out, spaced = [], {}, []
        for p in new:
            (spaced if len(p) > 1 and p[0] == " " and not p[-1].isspace() else alone).append(p)
        for at in range(0, len(spaced), self.JOINED):
            part = spaced[at : at + self.JOINED]
            e = self.tok.encode("".join(part), add_special_tokens=False)
            cuts = np.flatnonzero(np.diff(np.array(e.word_ids, np.int64), prepend=-1, append=-1)) * 4
            if len(cuts) != len(part) + 1:
                alone += part
                continue
            ids, cuts = array("I", e.ids).tobytes(), cuts.tolist()
            out.update((p, ids[a:b]) for p, a, b in zip(part, cuts, cuts[1:]))
        for at in range(0, len(alone), 10_000):
            part = alone[at : at + 10_000]
            out.update((p, array("I", e.ids).tobytes()) for p, e in zip(part, self.tok.encode_batch_fast(part, add_special_tokens=False)))
        return out

    def _by_pattern(self, texts: list[str]) -> list[bytes]:
        pieces = [self.split(t) for t in texts]
        return self._ids_of(pieces)

    def _ids_of(self, pieces: list[list[str]]) -> list[bytes]:
        """Ids of the pieces of each text, kept by whole pieces in a dictionary of bounded size."""
        new = list(set().union(*pieces) - self.odd.keys())
        made = self._encode(new)
        if len(self.odd) < self.KEEP_ODD:
            self.odd |= made
        return [b"".join([self.odd.get(p) or made[p] for p in ps]) for ps in pieces]

    def _whole(self, texts: list[str]) -> list[bytes]:
        return [array("I", e.ids).tobytes() for e in self.library.encode_batch_fast(texts, add_special_tokens=False)]

    def raw_ids(self, texts: list[str]) -> list[bytes]:
        """Ids of each text as little-endian unsigned 32-bit integers."""
        if not self.plain:
            return self._whole(texts)
        odd = [k for k, t in enumerate(texts) if any(a in t for a in self.added)]
        if not odd:
            return self._raw_ids(texts)
        out = self._raw_ids(["" if k in odd else t for k, t in enumerate(texts)])
        for k, ids in zip(odd, self._whole([texts[k] for k in odd])):
            out[k] = ids
        return out

    def _raw_ids(self, texts: list[str]) -> list[bytes]:
        raw = [t.encode("utf-8", "surrogatepass") for t in texts]
        cuts = np.concatenate([[0], np.cumsum([len(r) for r in raw])]).astype(np.int64)
        flat = np.frombuffer(b"".join(raw), np.uint8)
        out: list = [b""] * len(texts)
        if not len(flat):
            return out
        kind = self.KIND[flat]
        before = np.concatenate([[9], kind[:-1]]).astype(np.uint8)
        heads = cuts[:-1][np.diff(cuts) > 0]
        before[heads] = 9
        left = (kind == 5) | ((kind >= 3) & (before >= 3) & (before < 5))
        sign = np.flatnonzero((flat == 0x97) | (flat == 0xB7))  # the signs of multiplication and division are no letters
        left[sign[(flat[sign - 1] == 0xC3)]] = True
        bad = np.unique(np.searchsorted(cuts, np.flatnonzero(left), "right") - 1)
        for k, ids in zip(bad.tolist(), self._by_pattern([texts[k] for k in bad])):
            out[k] = ids
        begin = (kind != before) & ~((before == 3) & (kind <= 2))
        starts = np.flatnonzero(begin)
        ends = np.append(starts[1:], len(flat))
        text_of = np.searchsorted(cuts, starts, "right") - 1
        if len(bad):
            skip = np.zeros(len(texts), bool)
            skip[bad] = True
            keep = ~skip[text_of]
            starts, ends, text_of = starts[keep], ends[keep], text_of[keep]
        size = (ends - starts).astype(np.int32)
        whole, h = self._words(flat, starts, size)
        entry = self.store.find(h, whole, size)
        at, count = self.store.at[entry], self.store.count[entry]
        pool = self.store.pool
        new = np.flatnonzero(entry == 0)
        if len(new):
            wide = size[new] > Pieces.WIDE
            order = new[~wide]
            order = order[np.lexsort((size[order], whole[order, 2], whole[order, 1], whole[order, 0]))]
            first = np.ones(len(order), bool)  # the first of a run of equal pieces
            first[1:] = (whole[order][1:] != whole[order][:-1]).any(axis=1) | (size[order][1:] != size[order][:-1])
            lead, group = order[first], np.cumsum(first) - 1
            text = lambda k: flat[starts[k] : ends[k]].tobytes().decode("utf-8", "surrogatepass")
            long, n_short = new[wide], len(lead)
            words = [text(k) for k in lead.tolist()]
            made = self._encode(words)
            ids = [np.frombuffer(made[w], "<u4") for w in words]
            ids += [np.frombuffer(x, "<u4") for x in self._ids_of([[text(k)] for k in long.tolist()])]
            order, group = np.concatenate([order, long]), np.concatenate([group, n_short + np.arange(len(long))])
            lens = np.array([len(i) for i in ids], np.int64)
            pool_end = self.store.used
            pool = np.concatenate([pool[:pool_end], *ids])
            offs = pool_end + np.cumsum(lens) - lens
            at[order], count[order] = offs[group], lens[group]
            if self.store.n < self.store.most:
                for k, i in zip(lead.tolist(), ids):
                    self.store.add(int(h[k]), whole[k], int(size[k]), i)
        total = np.cumsum(count)
        if len(total) and total[-1]:
            ids = pool[np.repeat(at - (total - count), count) + np.arange(total[-1])]
            edges = np.searchsorted(text_of, np.arange(len(texts) + 1), "left")
            byte = np.concatenate([[0], total])[edges] * 4
            whole_ids = ids.tobytes()
            done = set(bad.tolist())
            for k in range(len(texts)):
                if k not in done:
                    out[k] = whole_ids[byte[k] : byte[k + 1]]
        return out

    def _words(self, flat: np.ndarray, starts: np.ndarray, size: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(first 24 bytes of each piece as three words, zeros behind its end; their hash, never 0). Wider pieces get a hash that
        no entry has, so they are never found in the store."""
        if not len(starts):
            return np.empty((0, 3), np.uint64), np.empty(0, np.uint64)
        view = np.lib.stride_tricks.sliding_window_view(np.concatenate([flat, np.zeros(Pieces.WIDE + 8, np.uint8)]), 8)
        whole = np.empty((len(starts), 3), np.uint64)
        whole[:, 0] = view[starts].view("<u8").reshape(-1) & EDGE[np.minimum(size, 8)]
        whole[:, 1:] = 0
        for k in (1, 2):
            more = np.flatnonzero(size > 8 * k)
            whole[more, k] = view[starts[more] + 8 * k].view("<u8").reshape(-1) & EDGE[np.clip(size[more] - 8 * k, 0, 8)]
        h = size.astype(np.uint64)
        for k, factor in enumerate(FACTORS):
            h = (h ^ whole[:, k]) * factor
            h ^= h >> np.uint64(31)
        h *= FACTORS[0]
        h |= np.uint64(1)
        h[size > Pieces.WIDE] = np.uint64(2)
        return whole, h


EDGE = np.array([(1 << (8 * n)) - 1 for n in range(9)], np.uint64)
FACTORS = (np.uint64(0x9E3779B97F4A7C15), np.uint64(0xBF58476D1CE4E5B9), np.uint64(0x94D049BB133111EB))


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def _blocks(tokenizer: str, end_id: int, block_ids: int):
    def run(batches):
        enc = encoder(tokenizer)
        bits, shard, number = id_bits(enc.vocab_size), TaskContext.get().partitionId(), 0
        held: list[bytes] = []
        docs: list[int | None] = []
        filled = 0
        end = array("I", [end_id]).tobytes()

        def flush():
            nonlocal held, docs, filled, number
            ids = np.frombuffer(b"".join(held), "<u4")
            row = {"shard": [shard], "block": [number], "bits": [bits], "n_ids": [len(ids)], "payload": [pack(ids, bits)], "doc_ids": [docs], "lengths": [[len(x) // 4 for x in held]]}
            held, docs, filled, number = [], [], 0, number + 1
            return pa.RecordBatch.from_pydict(row, schema=ARROW_BLOCKS)

        for batch in batches:
            keys, col = batch.column(0).to_pylist(), batch.column(1)
            at = 0
            while at < len(keys):
                texts, chars = [], 0
                while at + len(texts) < len(keys) and chars < FLUSH_CHARS:
                    texts.append(col[at + len(texts)].as_py())
                    chars += len(texts[-1])
                for key, raw in zip(keys[at : at + len(texts)], enc.raw_ids(texts)):
                    held.append(raw + end)
                    docs.append(key)
                    filled += len(held[-1]) // 4
                    if filled >= block_ids:
                        yield flush()
                at += len(texts)
        if docs:
            yield flush()

    return run


def write_token_file(docs: DataFrame, tokenizer: str, end_id: int = 0, block_ids: int = BLOCK_IDS, shards: int | None = None, order: list[str] | None = None) -> DataFrame:
    """Encode every text and write the token file in ascending `order` (doc_id, then text); returns its blocks, read back."""
    slim = docs.select(F.col("doc_id").cast("long").alias("doc_id"), F.coalesce(F.col("text").cast("string"), F.lit("")).alias("text"), *[F.col(c) for c in order or []])
    keys = list(order or ["doc_id"])
    if not order:
        slim = slim.withColumn("h_", F.xxhash64("text")).withColumn("n_", F.monotonically_increasing_id())
        keys += ["h_", "n_"]
    small_batches(docs.sparkSession)
    spread = slim.repartitionByRange(shards, *keys) if shards else slim.repartitionByRange(*keys)
    inside = keys if order else ["doc_id", "h_", "text"]
    blocks = spread.sortWithinPartitions(*inside).select("doc_id", "text").mapInArrow(lean(_blocks(tokenizer, end_id, block_ids)), BLOCKS)
    return written(blocks, "token-file")


def _rows(with_ids: bool):
    def run(batches):
        for batch in batches:
            for at in range(batch.num_rows):
                r = batch.slice(at, 1).to_pylist()[0]
                ids = unpack(r["payload"], r["bits"], r["n_ids"]).astype("<u4")
                cuts = np.concatenate([[0], np.cumsum(r["lengths"], dtype=np.int64)])
                mine = [ids[a:b] for a, b in zip(cuts, cuts[1:])]
                n = len(mine)
                arrays = [pa.array([r["shard"]] * n, pa.int32()), pa.array([r["block"]] * n, pa.int64()), pa.array(r["doc_ids"], pa.int64()), pa.array(cuts[:-1]), pa.array(r["lengths"], pa.int64()), pa.array([zlib.crc32(x.tobytes()) for x in mine], pa.int64())]
                if with_ids:
                    arrays.append(pa.array([x.astype(np.int64) for x in mine], pa.list_(pa.int64())))
                yield pa.RecordBatch.from_arrays(arrays, names=["shard", "block", "doc_id", "at", "n_tokens", "ids_crc32", "ids"][: len(arrays)])

    return run


def read_token_file(blocks: DataFrame, with_ids: bool = False) -> DataFrame:
    """Unpack the blocks: one row per document with its block, its place in it, its length and checksum, and its ids if asked for."""
    extra = ", ids array<long>" if with_ids else ""
    return blocks.select("shard", "block", "bits", "n_ids", "payload", "doc_ids", "lengths").mapInArrow(_rows(with_ids), f"shard int, block long, doc_id long, at long, n_tokens long, ids_crc32 long{extra}")


def block_starts(blocks: DataFrame) -> DataFrame:
    """(s_, b_, block_start): ids before each block. Sums run within shards; only one row a shard meets in one task."""
    before = blocks.groupBy("shard").agg(F.sum("n_ids").alias("n")).select(F.col("shard").alias("s0_"), (F.sum("n").over(Window.orderBy("shard")) - F.col("n")).alias("shard_start"))
    inner = Window.partitionBy("shard").orderBy("block")
    in_shard = blocks.select("shard", "block", (F.sum("n_ids").over(inner) - F.col("n_ids")).alias("in_shard"))
    return in_shard.join(before, F.col("shard") == F.col("s0_")).select(F.col("shard").alias("s_"), F.col("block").alias("b_"), (F.col("shard_start") + F.col("in_shard")).alias("block_start"))


def document_digests(blocks: DataFrame) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 of every document, all taken from the file's blocks."""
    docs = read_token_file(blocks)
    return docs.join(block_starts(blocks), (F.col("shard") == F.col("s_")) & (F.col("block") == F.col("b_"))).select("doc_id", (F.col("block_start") + F.col("at")).alias("start"), "n_tokens", "ids_crc32")
