"""Packing by powers of two: each document is cut into pieces of binary lengths, and equal lengths share a bucket.

A document is its token ids and one end id. It becomes whole windows of ``window`` ids and then the set bits of the rest
from the largest down, so every piece has a power-of-two length, fills a sequence of that length by itself, needs no
padding and never shares it with another document. Sequences of one length are numbered one after another, which makes
batches of equal length.

Null and empty texts are a document of the end id alone. Repeated rows are separate documents with separate sequences.
An empty table gives an empty result; columns other than doc_id and text are ignored. Whole texts are tokenised: text
is cut at ASCII white space, which this tokenizer drops, and the different chunks of a group of texts are tokenised
together, their words as columns of arrays. Nothing is kept from one group to the next.
"""

from __future__ import annotations

import json
import os
import zlib
from collections.abc import Iterator
from pathlib import Path
from unicodedata import is_normalized

import numpy as np
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import store, table

WINDOW = 2048
END_ID = 1
#: Bytes of texts whose different chunks are tokenised together, about.
GROUP = 1 << 22
#: Units merged together, and bytes of a unit and units of a length from which each is merged by itself.
BLOCK, LONG, FEW = 1 << 14, 48, 32
#: ASCII marks that may follow a word; not the apostrophe, which takes part in units of its own.
MARKS = b"!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~"
#: Pieces that one window numbers, about.
WINDOW_PIECES = 500_000
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long, ids binary"

MARK, LETTER = (np.isin(np.arange(256), np.frombuffer(x, np.uint8)) for x in (MARKS, b"ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz"))
LOWER = np.frombuffer(bytes(range(256)).lower(), np.uint8)
FREE = np.uint64(2**64 - 1)

_known: dict[str, tuple] = {}


def bytes_of(strings) -> tuple[np.ndarray, np.ndarray]:
    """Bytes of an Arrow array of strings without nulls, and where each begins, with the end of the last."""
    _, edges, raw = strings.buffers()
    edges = np.frombuffer(edges, np.int32)[strings.offset : strings.offset + len(strings) + 1].astype(np.int64) if len(strings) else np.zeros(1, np.int64)
    return np.frombuffer(raw or b"", np.uint8)[edges[0] : edges[-1]], edges - edges[0]


class Merger:
    """Byte-pair merges of many units at once. Units of one length are the columns of an array; each round merges the pair of least rank in every column, the leftmost of equal ones, and thereby shortens every column that goes on by one."""

    def __init__(self, model: dict, shown: dict[int, str]):
        vocab, end = model["vocab"], model["end_of_word_suffix"] or ""
        self.first, self.last = (np.array([vocab[shown[x] + e] for x in range(256)], np.int64) for e in ("", end))
        pairs = [m.split(" ") if isinstance(m, str) else m for m in model["merges"]]
        rank_of = {(vocab[a] << 32) + vocab[b]: rank for rank, (a, b) in enumerate(pairs)}
        self.made = np.array([vocab[a + b] for a, b in pairs], np.int64)
        self.none = len(pairs)
        # keys that another one keeps out of their slot move on to the next table
        self.tables: list[tuple] = []
        keys, ranks = np.array(list(rank_of), np.uint64), np.array(list(rank_of.values()), np.int64)
        while len(keys) or not self.tables:
            bits = max(1, (4 * len(keys)).bit_length())
            factor, shift = np.uint64((0x9E3779B97F4A7C15 * (2 * len(self.tables) + 1)) & (2**64 - 1)), np.uint64(64 - bits)
            slot = (keys * factor) >> shift
            held, rank = np.full(1 << bits, FREE, np.uint64), np.full(1 << bits, self.none, np.int32)
            held[slot] = keys
            won = held[slot] == keys
            rank[slot[won]] = ranks[won]
            self.tables.append((factor, shift, held, rank))
            keys, ranks = keys[~won], ranks[~won]

    @staticmethod
    def fits(model: dict, shown: dict[int, str]) -> bool:
        """Whether merges alone make this model's ids, and each byte has its own."""
        other = any(model.get(k) for k in ("dropout", "continuing_subword_prefix", "byte_fallback", "ignore_merges"))
        return model["type"] == "BPE" and not other and all(c + e in model["vocab"] for c in shown.values() for e in ("", model["end_of_word_suffix"] or ""))

    def ranks(self, left: np.ndarray, right: np.ndarray) -> np.ndarray:
        return self._found((left.astype(np.uint64) << np.uint64(32)) + right.astype(np.uint64))

    def _found(self, keys: np.ndarray, table: int = 0) -> np.ndarray:
        factor, shift, held, rank = self.tables[table]
        slot = (keys * factor) >> shift
        there = held[slot]
        out = np.where(there == keys, rank[slot], np.int32(self.none))
        rest = (there != keys) & (there != FREE)
        if table + 1 < len(self.tables) and rest.any():
            out[rest] = self._found(keys[rest], table + 1)
        return out

    def merge(self, raw: np.ndarray) -> Iterator[tuple[np.ndarray, np.ndarray]]:
        """Columns of ``raw``, whose rows are the bytes of units, and their ids: a row for each."""
        ids = np.concatenate([self.first[raw[:-1]], self.last[raw[-1:]]]).astype(np.int32)
        place = np.arange(raw.shape[1])
        rank = self.ranks(ids[:-1], ids[1:])
        row = np.arange(len(raw), dtype=np.int32)[:, None]
        while len(ids) > 1:
            n = len(ids)
            least = ((rank << 6) + row[: n - 1]).min(0)
            go = least < self.none << 6
            if not go.all():
                yield place[~go], ids[:, ~go].T
                place, ids, rank, least = place[go], ids[:, go], rank[:, go], least[go]
                if not len(place):
                    return
            k, made, col = least & 63, self.made[least >> 6].astype(np.int32), np.arange(len(place))
            ids = np.where(row[: n - 1] <= k, ids[:-1], ids[1:])
            ids[k, col] = made
            rank = np.where(row[: n - 2] < k, rank[:-1], rank[1:])
            has = np.flatnonzero(k > 0)
            rank[k[has] - 1, has] = self.ranks(ids[k[has] - 1, has], made[has])
            has = np.flatnonzero(k < n - 2)
            rank[k[has], has] = self.ranks(made[has], ids[k[has] + 1, has])
        yield place, ids.T


def gathered(flat: np.ndarray, at: np.ndarray, n: np.ndarray) -> np.ndarray:
    """The stretches of ``flat`` that begin at ``at`` and are ``n`` long, one after another."""
    ends = np.cumsum(n)
    return flat[np.repeat(at - ends + n, n) + np.arange(ends[-1] if len(ends) else 0)]


class ChunkTokenizer:
    """Ids of texts. Their different white-space chunks are cut into units, and the different units are merged together as arrays of bytes."""

    def __init__(self, path: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.model = self.tokenizer.model
        # the printable character that stands for each byte in a byte-level vocabulary
        plain = [x for x in range(256) if 33 <= x <= 126 or 161 <= x <= 172 or x >= 174]
        others = [x for x in range(256) if x not in plain]
        self.shown = {x: chr(x) for x in plain} | {x: chr(256 + k) for k, x in enumerate(others)}
        model = json.loads(Path(path).read_text())["model"]
        self.merger = Merger(model, self.shown) if Merger.fits(model, self.shown) else None

    def ids(self, texts) -> Iterator[np.ndarray]:
        """Ids of each text of an Arrow array of strings without nulls."""
        import pyarrow.compute as pc

        texts.validate(full=True)
        split = pc.ascii_split_whitespace(texts)
        coded = split.flatten().dictionary_encode()
        flat, at, n = self._chunks(coded.dictionary)
        codes, ends = coded.indices.to_numpy(), split.offsets.to_numpy() - split.offsets[0].as_py()
        for k in range(len(texts)):
            mine = codes[ends[k] : ends[k + 1]]
            yield gathered(flat, at[mine], n[mine])

    def _chunks(self, chunks) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of different chunks, and where those of each begin and how many they are."""
        import pyarrow as pa

        raw, edges = bytes_of(chunks)
        start, stop = edges[:-1], edges[1:]
        # a chunk's word ends before the marks that end the chunk
        last = np.arange(len(raw) + 1, dtype=np.int32)
        last[1:][MARK[raw]] = 0
        np.maximum.accumulate(last, out=last)
        word = np.maximum(start, last[stop])
        # letters of ASCII, and of Latin-1 as pairs of bytes; all other words are looked at one by one
        pair = np.concatenate([[False], raw[:-1] == 0xC3]) if len(raw) else raw > 0
        odd = np.zeros(len(raw) + 1, np.int32)
        np.cumsum(~(LETTER[raw] | (raw == 0xC3) | pair & (raw != 0x97) & (raw != 0xB7)), out=odd[1:])
        plain = (odd[word] == odd[start]) & (word > start)
        low = LOWER[raw]
        low[pair & (raw >= 0x80) & (raw <= 0x9E)] += 0x20
        others, more, rest = np.flatnonzero(~plain), [], []
        for c in chunks.take(pa.array(others)).cast(pa.binary()).to_pylist():
            w = c.rstrip(MARKS)
            # one run of letters is one unit of the tokenizer, and so is a run of marks after it (apostrophes are not among them)
            one = w.isalpha() or not w.isascii() and self._one_unit(w)
            more += [w.decode().lower().encode(), c[len(w) :]] if one else [b"", b""]
            rest += [] if one else [c.decode()]
            plain[others[len(more) // 2 - 1]] = one
        # words and tails take turns
        offsets = np.append(np.column_stack([start, word]).ravel(), len(raw)).astype(np.int32)
        units = pa.Array.from_buffers(pa.binary(), 2 * len(start), [None, pa.py_buffer(offsets), pa.py_buffer(low)])
        units = pa.concat_arrays([units, pa.array(more, pa.binary())]).dictionary_encode()
        code = units.indices.to_numpy().reshape(-1, 2)
        parts, code = code[: len(start)].copy(), code[len(start) :]
        parts[others] = code
        flat, at, n = self._units(units.dictionary, np.unique(parts[plain]))
        # what is no such word has its own ids, and no tail
        other = [e.ids for k in range(0, len(rest), 1024) for e in self.tokenizer.encode_batch(rest[k : k + 1024], add_special_tokens=False)]
        begin, count = at[parts], n[parts]
        count[~plain] = 0
        count[~plain, 0] = [len(x) for x in other]
        begin[~plain, 0] = len(flat) + np.cumsum(count[~plain, 0]) - count[~plain, 0]
        flat = np.concatenate([flat, np.array([t for x in other for t in x], np.uint32)])
        total = count.sum(1)
        return gathered(flat, begin.ravel(), count.ravel()), np.cumsum(total) - total, total

    @staticmethod
    def _one_unit(word: bytes) -> bool:
        text = word.decode()
        return text.isalpha() and text.lower().isalpha() and "\u03a3" not in text and is_normalized("NFC", text)

    def _units(self, units, used: np.ndarray) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
        """Ids of the used ones of lower-cased units, straight from the merges of the model, and where those of each begin and how many they are."""
        raw, edges = bytes_of(units)
        size = np.diff(edges)
        found, held = [np.zeros(0, np.uint32)], 0
        at, n = np.zeros(len(size), np.int64), np.zeros(len(size), np.int64)
        used = used[np.argsort(size[used], kind="stable")]
        for group in np.split(used, np.flatnonzero(np.diff(size[used])) + 1):
            length = int(size[group[0]]) if len(group) else 0
            if not length:
                continue
            if self.merger is None or length > LONG or len(group) < FEW:
                for u in group:
                    shown = "".join([self.shown[x] for x in raw[edges[u] : edges[u + 1]].tolist()])
                    found.append(np.array([t.id for t in self.model.tokenize(shown)], np.uint32))
                    at[u], n[u] = held, len(found[-1])
                    held += len(found[-1])
                continue
            for k in range(0, len(group), BLOCK):
                part = group[k : k + BLOCK]
                for place, ids in self.merger.merge(raw[edges[part] + np.arange(length)[:, None]]):
                    at[part[place]], n[part[place]] = held + ids.shape[1] * np.arange(len(ids)), ids.shape[1]
                    found.append(ids.astype(np.uint32).ravel())
                    held += ids.size
        return np.concatenate(found), at, n


def tokenizer_for(path: str) -> ChunkTokenizer:
    if path not in _known:
        _known.clear()
        _known[path] = ChunkTokenizer(path)
    return _known[path]


def grouped(texts, size: int = GROUP) -> Iterator:
    """Stretches of an Arrow array of strings that cover it and are full at ``size`` bytes."""
    import pyarrow.compute as pc

    ends, first = np.cumsum(pc.binary_length(texts).to_numpy(), dtype=np.int64), 0
    while first < len(texts):
        last = int(np.searchsorted(ends, size + (ends[first - 1] if first else 0))) + 1
        yield texts.slice(first, last - first)
        first = last


def cuts(n: int, window: int = WINDOW) -> list[tuple[int, int]]:
    """(start, length) of the pieces of n ids."""
    out = [(s, window) for s in range(0, n - n % window, window)]
    at, rest = n - n % window, n % window
    for bit in reversed(range(rest.bit_length())):
        if rest >> bit & 1:
            out.append((at, 1 << bit))
            at += 1 << bit
    return out


def pieces(docs: DataFrame, tokenizer_path: str | None = None, window: int = WINDOW, with_ids: bool = True) -> DataFrame:
    """One row for each piece; ``ids`` holds little-endian uint32 ids (null without ``with_ids``)."""
    if tokenizer_path is None:
        import public_tokenizers

        tokenizer_path = public_tokenizers.path("word_bpe_49k.json")
    end = END_ID.to_bytes(4, "little")

    def run(batches):
        import pyarrow as pa

        tok = tokenizer_for(tokenizer_path)
        schema = pa.schema([(c, pa.int64()) for c in ("doc_id", "start", "length", "ids_crc32", "doc_tokens")] + [("ids", pa.binary())])
        for batch in batches:
            ids_of = batch.column(0).to_pylist()
            rows: list[list] = [[], [], [], [], [], []]
            texts = batch.column(1).cast(pa.string()).fill_null("")
            for doc, ids in zip(ids_of, (ids for group in grouped(texts) for ids in tok.ids(group))):
                raw = memoryview(ids.astype("<u4").tobytes() + end)
                n = len(raw) // 4
                each = cuts(n, window)
                parts = [raw[4 * s : 4 * (s + k)] for s, k in each]
                rows[0] += [doc] * len(each)
                rows[1] += [s for s, _ in each]
                rows[2] += [k for _, k in each]
                rows[3] += [zlib.crc32(p) for p in parts]
                rows[4] += [n] * len(each)
                rows[5] += [bytes(p) for p in parts] if with_ids else [None] * len(each)
                if len(rows[0]) >= 8192:
                    yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(rows, schema)], schema=schema)
                    rows = [[], [], [], [], [], []]
            yield pa.RecordBatch.from_arrays([pa.array(c, f.type) for c, f in zip(rows, schema)], schema=schema)

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, PIECES)


def pack(docs: DataFrame, tokenizer_path: str | None = None, window: int = WINDOW, with_ids: bool = True) -> DataFrame:
    """Pieces with sequence_id (gapless; sequences of one length are neighbours) and offset, which is always 0."""
    cut = pieces(docs, tokenizer_path, window, with_ids)
    cut = store(cut if with_ids else cut.drop("ids"), "pieces")
    spread = max(16, -(-cut.count() // WINDOW_PIECES))
    cut = cut.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(spread)))
    # a row for each length and bucket: one task adds them up, and they may be broadcast (12 for each half million pieces)
    sizes = cut.groupBy("length", "bucket").count()
    before = sizes.select("length", "bucket", (F.sum("count").over(Window.orderBy(F.desc("length"), "bucket").rowsBetween(Window.unboundedPreceding, 0)) - F.col("count")).alias("before"))
    place = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "start", "ids_crc32"))
    out = cut.withColumn("place", place).join(F.broadcast(before), ["length", "bucket"])
    return out.withColumn("sequence_id", F.col("before") + F.col("place") - 1).withColumn("offset", F.lit(0).cast("long")).drop("bucket", "place", "before")


def query(spark, sf_dir):
    out = pack(table(spark, sf_dir, "documents", "doc_id", "text"), with_ids=False)
    return out.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", "sequence_id", "offset")
