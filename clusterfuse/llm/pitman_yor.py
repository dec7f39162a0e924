"""Text scores by a hierarchical Pitman-Yor language model.

A word is drawn in the restaurant of the word before it; all these restaurants share one parent, the word restaurant, and
its base measure spells words byte by byte in restaurants of three, two, one and no preceding bytes, each the parent of the
longer one, over a uniform base. Every text begins in the context of an end.

Seating is sampled by Gibbs sweeps at every level: given the base probability of a dish, the customers of a dish open
tables as in a Chinese restaurant process (all dishes of a sweep independently, given the last sweep's totals). Tables of
contexts are customers of the word restaurant, its tables are customers of the spelling restaurants and so on. Contexts
begin with one table for each word and are seated anew ``context_sweeps`` times; each time the restaurants above are sampled
again, and their predictive probabilities are averaged over the kept sweeps. A context's probabilities are linear in those
of the word restaurant, so averaging the latter averages both, given the contexts' last seating. The seats of a pair are
drawn from its hash, so that each block that holds the pair draws the same and no exchange of pairs is needed: only the
tables beyond the first of each pair, summed by word, are sent. Each block keeps its pairs' last seats to score with.

What moves: documents are read once into blocks of about ``BLOCK`` tokens, in which a word or a pair of words stands once
with its training count. Blocks ask about their pairs and words: asks are dealt by hash into parts of about ``PART_ASKS``
and packed (a row for each block and part, 4 bytes or so for a pair, so no pair, word or context is a hot key), a part adds
them up and answers each block in the order of its asks. Pairs are known by a hash whose width grows with the corpus (two
pairs are taken for one with odds below 1e-7). Bytes in contexts fall into 32 classes, so the spelling model has 32**3
restaurants of 257 dishes at most whatever the corpus: that bounds what is collected. A sample is broadcast as the seats
that it holds, packed; each worker works out its probabilities (34 MB a sample at most, much less in practice).

As in the base score, words that no training text holds are one further dish of the word restaurant. It gets the part of
the spelling model that the training words leave over, so the probabilities of the vocabulary and this dish add up to 1 in
every context.

Tokens are lower-cased words between ASCII white space and one end for each text. Null and empty texts are the end
alone; a row without doc_id trains (its text form is empty). Repeated rows are separate texts. Without training texts
every count is 0 and the model is its base. An empty table gives an empty result. Other columns are ignored.
"""

from __future__ import annotations

import math
import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..sources import tables
from .common import BLANK, CRC_TABLE, LOWER, UPPER, crc_sql, store, table
from .near_dup import _mix, word_hashes

BLOCK = 3_000_000
#: Pairs that are seated at once: what fits the caches.
SEATED = 1 << 13
#: Asks of a part, at most (three of five tokens or so make a pair of their block).
PART_ASKS, PART_TOKENS = 1_000_000, 2_500_000
SWEEPS, BURN_IN = 4, 1
CONTEXT_SWEEPS = 1
CLASSES, DEPTH, END = 32, 3, 256
DISHES = 257
CONTEXT_STRENGTH = 2.0
WORD_STRENGTH, SPELL_STRENGTH, SPELL_DISCOUNT = 10.0, 1.0, 0.5
BLOCKS = "block long, doc_id array<long>, held_out array<boolean>, n_tokens array<int>, size long, n_words long, ids binary, words binary, train binary"
_U = np.uint64


def _classes() -> np.ndarray:
    """Context class of each symbol: 0 before a word and for its end; letters have one each."""
    out = np.full(DISHES, 27, np.int64)
    out[97:123] = np.arange(1, 27)
    out[48:58] = 28
    out[0x80:0xC0] = 29
    out[0xC0:0xE0] = 30
    out[0xE0:0x100] = 31
    out[END] = 0
    return out


CLASS = _classes()


def held_out(doc_id) -> bool:
    return zlib.crc32(b"" if doc_id is None else str(doc_id).encode()) % 5 == 1


def pack(*columns: np.ndarray) -> bytes:
    """Whole numbers below 2**64 as bytes: the planes of equal significance stand together, which is what compresses. A byte for each column tells its planes."""
    import zstandard

    widths = [max(1, (int(c.max()).bit_length() + 7) // 8) if len(c) else 1 for c in columns]
    planes = [np.ascontiguousarray(c.astype("<u8").view(np.uint8).reshape(-1, 8)[:, :w].T).tobytes() for c, w in zip(columns, widths)]
    return zstandard.ZstdCompressor(level=1).compress(bytes(widths) + b"".join(planes))


def unpack(body: bytes, columns: int) -> list[np.ndarray]:
    import zstandard

    raw = np.frombuffer(zstandard.ZstdDecompressor().decompress(body), np.uint8)
    widths, at = raw[:columns].tolist(), columns
    n = (len(raw) - columns) // sum(widths)
    out = []
    for w in widths:
        full = np.zeros((n, 8), np.uint8)
        full[:, :w] = raw[at : at + n * w].reshape(w, n).T
        out.append(full.view("<u8").reshape(-1))
        at += n * w
    return out


class Numbers(dict):
    """Numbers of words in the order in which they are met."""

    def __missing__(self, word: bytes) -> int:
        self[word] = number = len(self)
        return number


def _press(raw: bytes) -> bytes:
    import zstandard

    return zstandard.ZstdCompressor(level=3).compress(raw)


def _words(body: bytes) -> list[bytes]:
    import zstandard

    return zstandard.ZstdDecompressor().decompress(body).split(b"\n")


def blocks(docs: DataFrame) -> DataFrame:
    """A row for each block: its documents, its words (the end is the empty one), their training counts, and the words' numbers token by token."""

    def run(batches):
        import pyarrow as pa
        from pyspark import TaskContext

        kinds = [pa.int64(), pa.list_(pa.int64()), pa.list_(pa.bool_()), pa.list_(pa.int32()), pa.int64(), pa.int64(), pa.binary(), pa.binary(), pa.binary()]
        names = ["block", "doc_id", "held_out", "n_tokens", "size", "n_words", "ids", "words", "train"]
        # partitions below 2**39, blocks of one below 2**24
        base, seq = (TaskContext.get().partitionId() if TaskContext.get() else 0) << 24, 0
        place = Numbers()
        docs_, tokens_, size = [], [], 0

        def flush():
            nonlocal place, docs_, tokens_, size, seq
            ids = np.concatenate(tokens_)
            trains = np.repeat([not d[1] for d in docs_], [d[2] for d in docs_])
            # frequent words get small numbers
            order = np.argsort(-np.bincount(ids, minlength=len(place)), kind="stable")
            rank = np.empty(len(place), np.int32)
            rank[order] = np.arange(len(place), dtype=np.int32)
            ids, words = rank[ids], list(place)
            train = np.bincount(ids[trains], minlength=len(place))
            cols = [base + seq, *[[d[k] for d in docs_] for k in range(3)], size, len(place), pack(ids), _press(b"\n".join([words[k] for k in order])), pack(train)]
            place, docs_, tokens_, size, seq = Numbers(), [], [], 0, seq + 1
            return pa.RecordBatch.from_arrays([pa.array([c], k) for c, k in zip(cols, kinds)], names=names)

        for batch in batches:
            for doc, text in zip(batch.column(0).to_pylist(), batch.column(1).cast(pa.binary())):
                tokens = (text.as_py() or b"").lower().split()
                tokens.append(b"")
                tokens_.append(np.fromiter(map(place.__getitem__, tokens), np.int32, len(tokens)))
                docs_.append((doc, held_out(doc), len(tokens)))
                size += len(tokens)
                if size >= BLOCK:
                    yield flush()
        if docs_:
            yield flush()

    return docs.select(F.col("doc_id").cast("long"), "text").mapInArrow(run, BLOCKS)


def pair_keys(ids: np.ndarray, end: int | None = None) -> np.ndarray:
    """The word before each token and the token as one number. Texts end with the end, so the one before a text is that of the text before it."""
    before = np.empty_like(ids)
    before[1:], before[0] = ids[:-1], ids[-1] if end is None else end
    keys = before.astype(np.int64)
    keys <<= 32
    keys |= ids
    return keys


def _order(keys: np.ndarray, bits: int) -> np.ndarray:
    """Stable order of whole numbers below 2**bits. They are sorted together with their places, as far as both fit one number, which is faster than an argsort."""
    place = len(keys).bit_length()
    drop = max(0, bits + place - 64)
    joint = keys.astype(_U)
    joint >>= _U(drop)
    joint <<= _U(place)
    joint |= np.arange(len(keys), dtype=np.uint32)
    joint.sort()
    joint &= _U((1 << place) - 1)
    order = joint.view(np.int64)
    if drop:
        found = keys[order]
        if (found[1:] < found[:-1]).any():  # keys that differ in dropped bits alone; equal ones are in order
            order = order[np.argsort(found, kind="stable")]
    return order


def _numbered(keys: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Distinct keys of ``pair_keys`` and each key's number among them, as np.unique gives them, in less memory."""
    # without the zeros between its two numbers a key leaves room for its place
    low = (int(np.bitwise_or.reduce(keys)) & 0xFFFFFFFF).bit_length()
    short = keys >> 32
    short <<= low
    np.bitwise_or(short, keys & ((1 << low) - 1), out=short)
    order = _order(short, int(short.max(initial=0)).bit_length())
    del short
    keys = keys[order]
    new = np.ones(len(keys), bool)
    np.not_equal(keys[1:], keys[:-1], out=new[1:])
    number = np.empty(len(keys), np.int32)
    ranks = np.cumsum(new, dtype=np.int32)
    ranks -= 1
    number[order] = ranks
    return keys[new], number


class Block:
    """A block as its row holds it, with its pairs and words in the order of their asks."""

    def __init__(self, row, parts: int, word_parts: int, bits: int, asks: bool = True):
        """``asks``: also what tells how pairs are asked about, which only steps that read answers on pairs need."""
        import pyarrow as pa

        get = lambda k: row[k][0].as_py()
        self.doc_id, self.held_out, self.n_tokens = get("doc_id"), np.array(get("held_out"), bool), np.array(get("n_tokens"), np.int64)
        self.ids = unpack(get("ids"), 1)[0].astype(np.int32)
        self.words, self.train = _words(get("words")), unpack(get("train"), 1)[0].astype(np.int64)
        hashes = np.empty(len(self.words), _U)
        # hashes of the words; the empty one, which white space would hide, has a number of its own
        empty = self.words.index(b"")
        named = np.array([k for k in range(len(self.words)) if k != empty], np.int64)
        for at in range(0, len(named), 1 << 16):
            part = named[at : at + (1 << 16)]
            hashes[part] = word_hashes(b" ".join([self.words[k] for k in part]))
        hashes[empty] = _U(0x5851F42D4C957F2D)
        self.word_part = (_mix(hashes) % _U(word_parts)).astype(np.int64)
        self.word_order = _order(self.word_part, word_parts.bit_length())
        keys, self.pair = _numbered(pair_keys(self.ids))
        self.u, self.w = (keys >> 32).astype(np.int32), (keys & 0xFFFFFFFF).astype(np.int32)
        del keys
        if not asks:
            return
        trains = np.repeat(~self.held_out, self.n_tokens)
        self.times = np.bincount(self.pair[trains], minlength=len(self.u))
        # two words of a block with one hash would share it, and so might two pairs; the order among them is that of the numbers
        self.hash = _mix(hashes[self.u] * _U(0x9E3779B97F4A7C15) + _mix(hashes)[self.w]) >> _U(64 - bits)
        # parts are stretches of the hash, so one order serves both
        self.pair_part = ((self.hash >> _U(bits - 32)) * _U(parts) >> _U(32)).astype(np.int32)
        self.pair_order = _order(self.hash, bits)

    def pair_asks(self):
        """(part, body) of hashes and training counts."""
        for part, at in _runs(self.pair_part[self.pair_order]):
            mine = self.pair_order[at]
            yield part, pack(np.diff(self.hash[mine], prepend=_U(0)), self.times[mine])

    def word_asks(self, followers: np.ndarray, before: np.ndarray):
        """(part, words, body) of training counts, owned followers and owned words before."""
        for part, at in _runs(self.word_part[self.word_order]):
            mine = self.word_order[at]
            yield part, _press(b"\n".join([self.words[k] for k in mine])), pack(self.train[mine], followers[mine], before[mine])


def _runs(sorted_: np.ndarray):
    """(value, slice) of each run of equal values."""
    edge = np.flatnonzero(np.diff(sorted_, prepend=sorted_[:1] - 1))
    for lo, hi in zip(edge, np.append(edge[1:], len(sorted_))):
        yield int(sorted_[lo]), slice(lo, hi)


def pair_answers(held: DataFrame, parts: int, word_parts: int, bits: int) -> DataFrame:
    """block, part, body: the total count of each asked pair, and whether the block owns it (is the first to train it); and once, twice: pairs of the part with such counts."""

    def ask(batches):
        import pyarrow as pa

        for batch in batches:
            for k in range(batch.num_rows):
                row = batch.slice(k, 1)
                rows = list(Block(row, parts, word_parts, bits).pair_asks())
                for at in range(0, len(rows), 64):
                    some = rows[at : at + 64]
                    yield pa.RecordBatch.from_arrays([pa.array([p for p, _ in some], pa.int64()), pa.array([row["block"][0].as_py()] * len(some), pa.int64()), pa.array([b for _, b in some], pa.binary())], names=["part", "block", "body"])

    def answer(t):
        import pyarrow as pa

        order = np.argsort(t["block"].to_numpy())
        blocks_, bodies = t["block"].to_numpy()[order], t["body"].to_pylist()
        asked = [unpack(bodies[k], 2) for k in order]
        size = np.array([len(h) for h, _ in asked])
        hashes, times = np.concatenate([np.cumsum(h, dtype=_U) for h, _ in asked]), np.concatenate([c for _, c in asked]).astype(np.int64)
        distinct, where = np.unique(hashes, return_inverse=True)
        total = np.bincount(where, times, len(distinct)).astype(np.int64)
        owner = np.zeros(len(hashes), bool)
        trains = np.flatnonzero(times > 0)
        owner[trains[np.unique(where[trains], return_index=True)[1]]] = True
        begin = np.concatenate([[0], np.cumsum(size)])
        body = [pack(total[where[a:b]], owner[a:b]) for a, b in zip(begin, begin[1:])]
        first = np.arange(len(order)) == 0
        return pa.table({"block": pa.array(blocks_, pa.int64()), "part": pa.array([t["part"][0].as_py()] * len(order), pa.int64()), "body": pa.array(body, pa.binary()), "once": pa.array(first * int((total == 1).sum()), pa.int64()), "twice": pa.array(first * int((total == 2).sum()), pa.int64())})

    asks = held.select("block", "doc_id", "held_out", "n_tokens", "ids", "words", "train").mapInArrow(ask, "part long, block long, body binary")
    return asks.groupBy("part").applyInArrow(answer, "block long, part long, body binary, once long, twice long")


def _answered(answers, kind: int, n: int) -> list[np.ndarray]:
    """Columns of the answers of one kind, in the order of the block's asks."""
    parts, bodies, kinds = answers["part"].to_pylist(), answers["body"].to_pylist(), answers["kind"].to_pylist()
    mine = sorted(k for k in range(len(parts)) if kinds[k] == kind)
    mine.sort(key=lambda k: parts[k])
    found = [unpack(bodies[k], n) for k in mine]
    return [np.concatenate([f[i] for f in found]) for i in range(n)]


def word_asks(held: DataFrame, answers: DataFrame, parts: int, word_parts: int, bits: int) -> DataFrame:
    """part, block, words, body: what each block knows of its words, distinct pairs counted by their owners."""

    def run(row, answers_):
        import pyarrow as pa

        b = Block(row, parts, word_parts, bits)
        _, owner = _answered(answers_, 0, 2)
        own = b.pair_order[owner.astype(bool)]
        followers, before = np.bincount(b.u[own], minlength=len(b.words)), np.bincount(b.w[own], minlength=len(b.words))
        rows = list(b.word_asks(followers, before))
        return pa.table({"part": pa.array([r[0] for r in rows], pa.int64()), "block": pa.array([row["block"][0].as_py()] * len(rows), pa.int64()), "words": pa.array([r[1] for r in rows], pa.binary()), "body": pa.array([r[2] for r in rows], pa.binary())})

    mine = held.select("block", "doc_id", "held_out", "n_tokens", "ids", "words", "train")
    theirs = answers.select(F.col("block").alias("to"), "part", "body", F.lit(0).alias("kind"))
    return mine.groupBy("block").cogroup(theirs.groupBy("to")).applyInArrow(run, "part long, block long, words binary, body binary")


def word_types(asks: DataFrame) -> DataFrame:
    """part, word, n (training count), followers (distinct words after it), c (distinct words before it: its customers)."""

    def run(t):
        import pyarrow as pa

        place = Numbers()
        sums = np.zeros((3, 1024), np.int64)
        for words, body in zip(t["words"].to_pylist(), t["body"].to_pylist()):
            at = np.array(list(map(place.__getitem__, _words(words))), np.int64)
            if sums.shape[1] < len(place):
                sums = np.concatenate([sums, np.zeros((3, max(len(place), 2 * sums.shape[1]) - sums.shape[1]), np.int64)], axis=1)
            for s, x in zip(sums, unpack(body, 3)):
                s[at] += x.astype(np.int64)  # a block asks about a word once
        n = len(place)
        return pa.table({"part": pa.array([t["part"][0].as_py()] * n, pa.int64()), "word": pa.array([w.decode() for w in place], pa.string()), "n": pa.array(sums[0, :n]), "followers": pa.array(sums[1, :n]), "c": pa.array(sums[2, :n])})

    return asks.groupBy("part").applyInArrow(run, "part long, word string, n long, followers long, c long")


def tables_for(customers: np.ndarray, weight: np.ndarray, discount: float, rng: np.random.Generator) -> np.ndarray:
    """Sampled numbers of tables: customer i + 1 opens one with odds ``weight`` to i - discount * tables.

    Beyond 64 customers they come in groups of a 32nd of those seated, with the group's odds held fixed."""
    t = (customers > 0).astype(np.float64)
    order = np.argsort(-customers, kind="stable")
    c, w, s = customers[order], weight[order], t[order]
    i = 1
    while len(c) and i < c[0]:
        step = 1 if i < 64 else i // 32
        live = int(np.searchsorted(-c, -i, side="left"))  # those with more than i customers
        if not live:
            break
        n = np.minimum(step, c[:live] - i)
        p = w[:live] / (w[:live] + i - discount * s[:live])
        s[:live] += (rng.random(live) < p) if step == 1 else rng.binomial(n.astype(np.int64), np.clip(p, 0, 1))
        i += step
    t[order] = s
    return t


class Spelling:
    """Predictive probabilities of one sample of the spelling restaurants.

    What is pickled is the customers and tables that were seated (hundreds of kB); the probabilities (tens of MB) are worked
    out where they are first asked for, so that broadcasts of samples take next to no disk."""

    def __init__(self, seated: list):
        self.seated = seated  # cells (context * DISHES + symbol), customers and tables of each depth, the shortest contexts first
        self.row = None

    def __getstate__(self):
        return [pack(np.diff(cells, prepend=0), c, t) for cells, c, t in self.seated]

    def __setstate__(self, bodies):
        columns = [unpack(body, 3) for body in bodies]
        self.__init__([(np.cumsum(cells, dtype=np.int64), c.astype(np.float64), t.astype(np.float64)) for cells, c, t in columns])

    def levels(self) -> list[np.ndarray]:
        """Probabilities after every context of each depth but the last; unseated restaurants predict as their parents do."""
        above, out = np.full((1, DISHES), 1 / DISHES), []
        for depth in range(DEPTH):
            rows, probs = _predicted(*self.seated[depth], above, depth)
            above = np.tile(above, (CLASSES**depth // len(above), 1))
            above[rows] = probs
            out.append(above)
        return out

    def _build(self) -> None:
        above = self.levels()[-1]
        cells, c, t = self.seated[DEPTH]
        rows = np.unique(cells // DISHES)
        self.short, self.probs = above.astype(np.float32), np.empty((len(rows), DISHES), np.float32)  # of all one byte shorter; of seated restaurants at full depth
        for at in range(0, len(rows), 2048):
            some = rows[at : at + 2048]
            mine = slice(*np.searchsorted(cells, [some[0] * DISHES, (some[-1] + 1) * DISHES]))
            self.probs[at : at + 2048] = _predicted(cells[mine], c[mine], t[mine], above, DEPTH)[1]
        self.row = np.full(CLASSES**DEPTH, -1, np.int32)
        self.row[rows] = np.arange(len(rows), dtype=np.int32)

    def log10(self, context: np.ndarray, symbol: np.ndarray) -> np.ndarray:
        if self.row is None:
            self._build()
        row = self.row[context]
        out = np.where(row >= 0, self.probs[np.maximum(row, 0), symbol] if len(self.probs) else 0, self.short[context % CLASSES ** (DEPTH - 1), symbol])
        return np.log10(out)


def _predicted(cells: np.ndarray, c: np.ndarray, t: np.ndarray, above: np.ndarray, depth: int) -> tuple[np.ndarray, np.ndarray]:
    """(contexts, probabilities) of the seated restaurants of a depth, given the probabilities one byte shorter."""
    d, theta = SPELL_DISCOUNT, SPELL_STRENGTH
    rows, inverse = np.unique(cells // DISHES, return_inverse=True)
    n = len(rows)
    total, tabs = np.bincount(inverse, c, n), np.bincount(inverse, t, n)
    held = np.zeros((n, DISHES))
    held[inverse, cells % DISHES] = c - d * t
    up = above[rows % CLASSES ** (depth - 1)] if depth else np.repeat(above, n, 0)
    return rows, (held + (theta + d * tabs)[:, None] * up) / (theta + total)[:, None]


def spelled(words) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(context, symbol, start of each word) over the symbols of an Arrow string array without nulls."""
    import pyarrow as pa

    raw = words.cast(pa.large_binary())
    offsets = np.frombuffer(raw.buffers()[1], np.int64)[raw.offset : raw.offset + len(raw) + 1]
    body = np.frombuffer(raw.buffers()[2], np.uint8)[offsets[0] : offsets[-1]] if raw.buffers()[2] is not None else np.zeros(0, np.uint8)
    ends = offsets[1:] - offsets[0]
    symbol = np.insert(body.astype(np.int64), ends, END)
    start = np.concatenate([[0], ends + np.arange(1, len(ends) + 1)])[:-1]
    place = np.arange(len(symbol)) - np.repeat(start, np.diff(np.append(start, len(symbol))))
    kind = CLASS[symbol]
    context = np.zeros(len(symbol), np.int64)
    for k in range(1, DEPTH + 1):
        back = np.concatenate([np.zeros(k, np.int64), kind[:-k]])[: len(symbol)]
        context += np.where(place >= k, back, 0) * CLASSES ** (k - 1)
    return context, symbol, start


def spelling_of(cells: np.ndarray, counts: np.ndarray, last: Spelling | None, rng: np.random.Generator) -> Spelling:
    """Seat ``counts`` customers of each cell (context * DISHES + symbol), upwards; last: the last sweep's sample."""
    d, theta = SPELL_DISCOUNT, SPELL_STRENGTH
    before, seated = last.levels() if last else None, []
    for depth in range(DEPTH, -1, -1):
        context, dish = cells // DISHES, cells % DISHES
        if last is None:
            t = (counts > 0).astype(np.float64)
        else:
            old_cells, _, old_t = last.seated[depth]
            old_t = np.bincount(old_cells // DISHES, old_t, CLASSES**depth)
            parent = before[depth - 1][context % CLASSES ** (depth - 1), dish] if depth else np.full(len(cells), 1 / DISHES)
            t = tables_for(counts, (theta + d * old_t[context]) * parent, d, rng)
        seated.append((cells, counts, t))
        if depth:
            cells, back = np.unique(context % CLASSES ** (depth - 1) * DISHES + dish, return_inverse=True)
            counts = np.bincount(back, t, len(cells))
    return Spelling(seated[::-1])


class Sample:
    """One sweep: spelling, tables of all words, and the law of the word restaurant."""

    def __init__(self, spelling: Spelling, tables: float, total: float, discount: float, sweep: int):
        self.spelling, self.tables, self.total, self.discount, self.sweep = spelling, tables, total, discount, sweep
        self.taken = 0.0  # spelling probability of all training words
        self.seats = tables  # tables of all words as word_scores seats them

    def spell(self, words) -> np.ndarray:
        """log10 probability of the spelling of each word."""
        context, symbol, start = spelled(words)
        return np.add.reduceat(self.spelling.log10(context, symbol).astype(np.float64), start) if len(start) else np.zeros(0)

    def weight(self, spell: np.ndarray) -> np.ndarray:
        return (WORD_STRENGTH + self.discount * self.tables) * 10.0**spell

    def seat(self, words, counts: np.ndarray, weight: np.ndarray) -> np.ndarray:
        rng = np.random.default_rng([self.sweep, len(counts), zlib.crc32(words[0].as_py().encode()) if len(counts) else 0])
        return tables_for(counts, weight, self.discount, rng)


def _batches(batches):
    """(words, counts) of Arrow batches as contiguous arrays."""
    for b in batches:
        if b.num_rows:
            yield b.column(0), b.column(1).to_numpy(zero_copy_only=False).astype(np.int64), *b.columns[2:]


def sampled(types: DataFrame, total: int, discount: float) -> list[Sample]:
    """The kept samples, from types (word, c)."""
    sc = types.sparkSession.sparkContext
    known = types.filter("c > 0").select("word", "c")
    rng, kept, current, spelling = np.random.default_rng(7), [], None, None
    for sweep in range(SWEEPS + 1):
        shared = sc.broadcast(current)

        def count(batches):
            import pyarrow as pa

            model, cells, seats = shared.value, np.zeros(CLASSES**DEPTH * DISHES, np.int64), 0.0
            for words, c in _batches(batches):
                t = np.ones(len(c)) if model is None else model.seat(words, c, model.weight(model.spell(words)))
                context, symbol, start = spelled(words)
                np.add.at(cells, context * DISHES + symbol, np.repeat(t, np.diff(np.append(start, len(symbol)))).astype(np.int64))
                seats += t.sum()
            at = np.flatnonzero(cells)
            yield pa.RecordBatch.from_arrays([pa.array(np.append(at, -1)), pa.array(np.append(cells[at], int(seats)))], names=["cell", "n"])

        # 32**3 * 257 cells at most, whatever the corpus
        found = known.mapInArrow(count, "cell long, n long").groupBy("cell").agg(F.sum("n").alias("n")).toPandas().sort_values("cell")
        cell, n = found["cell"].to_numpy(), found["n"].to_numpy().astype(np.float64)
        tables = float(n[cell == -1].sum())
        shared.destroy()  # its file on the driver would stay to the end
        spelling = spelling_of(cell[cell >= 0], n[cell >= 0], spelling, rng)
        current = Sample(spelling, tables, float(total), discount, sweep)
        if sweep > BURN_IN:
            kept.append(current)
    shared = sc.broadcast(kept)

    def taken(batches):
        import pyarrow as pa

        mass, seats = np.zeros(len(shared.value)), np.zeros(len(shared.value))
        for words, c in _batches(batches):
            for k, m in enumerate(shared.value):
                spell = m.spell(words)
                mass[k] += float((10.0 ** spell[c > 0]).sum())
                seats[k] += m.seat(words, c, m.weight(spell)).sum()
        yield pa.RecordBatch.from_arrays([pa.array(range(len(mass)), pa.int32()), pa.array(mass), pa.array(seats)], names=["k", "mass", "seats"])

    # over all types, as word_scores reads them, so that both seat every word alike
    for k, mass, seats in types.select("word", "c").mapInArrow(taken, "k int, mass double, seats double").groupBy("k").agg(F.sum("mass"), F.sum("seats")).collect():
        kept[k].taken, kept[k].seats = min(mass, 1 - 1e-9), seats
    shared.destroy()
    return kept


def word_law(types: DataFrame, samples: list[Sample]) -> DataFrame:
    """``types`` (part, word, n, followers, c) with p: the predictive probability of the word restaurant, averaged over samples."""
    shared = types.sparkSession.sparkContext.broadcast(samples)

    def run(batches):
        import pyarrow as pa

        for words, c, *rest in _batches(batches):
            mean = np.zeros(len(c))
            for s in shared.value:
                spell = s.spell(words)
                spell[c == 0] = math.log10(1 - s.taken)
                t = s.seat(words, c, s.weight(spell))
                new = (WORD_STRENGTH + s.discount * s.seats) * 10.0**spell
                mean += (np.maximum(c - s.discount * t, 0) + new) / (s.total + WORD_STRENGTH) / len(shared.value)
            yield pa.RecordBatch.from_arrays([rest[0], words, rest[1], rest[2], pa.array(c), pa.array(np.maximum(mean, 1e-300))], names=["part", "word", "n", "followers", "c", "p"])

    return types.select("word", "c", "part", "n", "followers").mapInArrow(run, "part long, word string, n long, followers long, c long, p double")


def word_answers(asks: DataFrame, law: DataFrame) -> DataFrame:
    """block, part, body: training count, distinct followers and probability (the bits of a double) of each asked word."""

    def run(asked, known):
        import pyarrow as pa

        place = {w: k for k, w in enumerate(known["of"].cast(pa.binary()).to_pylist())}
        columns = [known["n"].to_numpy().astype(_U), known["followers"].to_numpy().astype(_U), known["p"].to_numpy().astype("<f4").view("<u4").astype(_U)]
        bodies = []
        for words in asked["words"].to_pylist():
            at = np.array([place[w] for w in _words(words)], np.int64)
            bodies.append(pack(*[c[at] for c in columns]))
        return pa.table({"block": asked["block"].combine_chunks(), "part": asked["part"].combine_chunks(), "body": pa.array(bodies, pa.binary())})

    theirs = law.select(F.col("part").alias("held_by"), F.col("word").alias("of"), "n", "followers", "p")
    return asks.select("part", "block", "words").groupBy("part").cogroup(theirs.groupBy("held_by")).applyInArrow(run, "block long, part long, body binary")


def _uniform(hashes: np.ndarray, draw: int) -> np.ndarray:
    return ((_mix(hashes + _U((draw * 0x9E3779B97F4A7C15) % 2**64)) >> _U(11)).astype(np.float64) + 0.5) * 2.0**-53


def _successes(n: np.ndarray, p: np.ndarray, u: np.ndarray, v: np.ndarray) -> np.ndarray:
    """Binomial numbers from uniform ones: by inversion, and by the normal law where the variance is above 9."""
    n, p = np.broadcast_to(n, u.shape).astype(np.float64), np.clip(p, 1e-300, 1 - 1e-12)
    wide = n * p * (1 - p) > 9
    q = np.minimum(p, 1 - p)
    k, at = np.zeros(len(u)), np.flatnonzero(~wide)
    mass = np.exp(n[at] * np.log1p(-q[at]))
    left, j = u[at] - mass, 0
    while len(at := at[keep := (left > 0) & (j < n[at])]):
        k[at] += 1
        mass = mass[keep] * (n[at] - j) / (j + 1) * q[at] / (1 - q[at])
        left, j = left[keep] - mass, j + 1
    at = np.flatnonzero(wide)
    z = np.sqrt(-2 * np.log(u[at])) * np.cos(2 * np.pi * v[at])
    k[at] = np.clip(np.rint(n[at] * q[at] + z * np.sqrt(n[at] * q[at] * (1 - q[at]))), 0, n[at])
    return np.where(p > 0.5, n - k, k)


def seated(customers: np.ndarray, weight: np.ndarray, discount: float, hashes: np.ndarray, sweep: int) -> np.ndarray:
    """As tables_for, but each dish's tables follow from its hash, whatever other dishes stand beside it."""
    out = (customers > 0).astype(np.float64)
    order = np.flatnonzero(customers > 1)
    order = order[np.argsort(-customers[order], kind="stable")]
    for at in range(0, len(order), SEATED):
        some = order[at : at + SEATED]
        out[some] = _seated(customers[some], weight[some].astype(np.float64), discount, _mix(hashes[some] + _U(sweep + 1)))
    return out


def _seated(c: np.ndarray, w: np.ndarray, discount: float, h: np.ndarray) -> np.ndarray:
    """Tables of dishes of two customers and more, those of most customers first."""
    s = np.ones(len(c))
    i, draw = 1, 0
    while i < c[0]:
        live, step = int(np.searchsorted(-c, -i, side="left")), 1 if i < 64 else i // 32
        p = w[:live] / (w[:live] + i - discount * s[:live])
        u = _uniform(h[:live], draw)
        s[:live] += u < p if step == 1 else _successes(np.minimum(step, c[:live] - i), p, u, _uniform(h[:live], draw + 1))
        i, draw = i + step, draw + 2
    return s


def _seats(b: Block, answers, discount: float, sweep: int):
    """(training count, tables, owned or not) of the block's pairs, and (training count, tables before this sweep, probability) of its words."""
    pair_n, owner = np.empty(len(b.u), np.int64), np.empty(len(b.u), bool)
    pair_n[b.pair_order], owner[b.pair_order] = _answered(answers, 0, 2)
    words = _word_columns(b, answers, 1)
    weight = (CONTEXT_STRENGTH + discount * words[1][b.u]) * words[2][b.w]
    return pair_n, seated(pair_n, weight, discount, b.hash, sweep), owner, words


def _word_columns(b: Block, answers, kind: int):
    n, tables, p = np.empty(len(b.words), np.int64), np.empty(len(b.words), np.int64), np.empty(len(b.words))
    n[b.word_order], tables[b.word_order], bits_of = (x.astype(np.int64) for x in _answered(answers, kind, 3))
    p[b.word_order] = bits_of.astype("<u4").view("<f4")
    return n, tables, p


def further_tables(held: DataFrame, told: DataFrame, known: DataFrame, parts: int, word_parts: int, bits: int, discount: float, sweep: int) -> DataFrame:
    """part, block, words, body: tables beyond the first of the pairs that each block owns, by the word before and by the word; words without any are left out.

    Part -1 holds the training counts and tables of all pairs of a block, in the order of its pairs, so that scores need not seat them again."""

    def run(row, answers):
        import pyarrow as pa

        b = Block(row, parts, word_parts, bits)
        pair_n, tables, owner, _ = _seats(b, answers, discount, sweep)
        own = np.flatnonzero(owner & (tables > 1))
        sums = [np.bincount(x[own], tables[own] - 1, len(b.words)).astype(np.int64) for x in (b.u, b.w)]
        order = b.word_order[(sums[0] + sums[1])[b.word_order] > 0]
        rows = [(part, _press(b"\n".join([b.words[k] for k in order[at]])), pack(sums[0][order[at]], sums[1][order[at]])) for part, at in _runs(b.word_part[order])]
        rows.append((-1, None, pack(pair_n, tables)))
        return pa.table({"part": pa.array([r[0] for r in rows], pa.int64()), "block": pa.array([row["block"][0].as_py()] * len(rows), pa.int64()), "words": pa.array([r[1] for r in rows], pa.binary()), "body": pa.array([r[2] for r in rows], pa.binary())})

    mine = held.select("block", "doc_id", "held_out", "n_tokens", "ids", "words", "train")
    theirs = _told(told, known)
    return mine.groupBy("block").cogroup(theirs.groupBy("to")).applyInArrow(run, "part long, block long, words binary, body binary")


def _told(told: DataFrame, *known: DataFrame) -> DataFrame:
    """Answers to each block: kind 0 of pairs, 1 and on of words."""
    out = told.select(F.col("block").alias("to"), "part", "body", F.lit(0).alias("kind"))
    for k, x in enumerate(known):
        out = out.unionByName(x.select(F.col("block").alias("to"), "part", "body", F.lit(k + 1).alias("kind")))
    return out


def with_further(types: DataFrame, further: DataFrame) -> DataFrame:
    """``types`` of one table for each pair, with the further tables in followers (tables of a word's context) and c."""

    def run(known, extra):
        import pyarrow as pa

        words = known["word"].cast(pa.binary()).to_pylist()
        place = {w: k for k, w in enumerate(words)}
        sums = np.zeros((2, len(words)), np.int64)
        for asked, body in zip(extra["words"].to_pylist(), extra["body"].to_pylist()):
            at = np.array([place[w] for w in _words(asked)], np.int64)
            for s, x in zip(sums, unpack(body, 2)):
                s[at] += x.astype(np.int64)
        return pa.table({"part": known["part"], "word": known["word"], "n": known["n"], "followers": pa.array(known["followers"].to_numpy() + sums[0]), "c": pa.array(known["c"].to_numpy() + sums[1])})

    return types.groupBy("part").cogroup(further.filter("part >= 0").groupBy("part")).applyInArrow(run, "part long, word string, n long, followers long, c long")


def _freed(spark, *stored: DataFrame) -> None:
    """Remove stored tables that nothing reads any more, and let Spark's cleaner find the shuffle files of finished steps: it acts on what the JVM collects."""
    import gc

    tables.discard(*stored)
    gc.collect()
    spark.sparkContext._jvm.System.gc()


def _discount(once: int, twice: int) -> float:
    return min(0.95, max(0.05, once / max(once + 2 * twice, 1)))


def language_scores(docs: DataFrame, context_sweeps: int = 0) -> DataFrame:
    """doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score for each row of ``docs`` (doc_id, text).

    Without ``context_sweeps`` contexts keep the seating that they begin with, one table for each word; the query seats them."""
    held = store(blocks(docs), "blocks")
    tokens, words = (int(x) for x in held.agg(F.coalesce(F.sum("size"), F.lit(0)), F.coalesce(F.sum("n_words"), F.lit(0))).first())
    parts, word_parts = max(1, -(-tokens // PART_TOKENS)), max(1, -(-words // PART_ASKS))
    bits = min(64, max(32, tokens.bit_length() + 25))
    told = store(pair_answers(held, parts, word_parts, bits), "pair-answers")
    _freed(docs.sparkSession)
    asks = store(word_asks(held, told, parts, word_parts, bits), "word-asks")
    _freed(docs.sparkSession)
    types = store(word_types(asks), "types")
    of = types.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count_if(F.col("n") > 0), F.coalesce(F.sum("c"), F.lit(0)), F.count_if(F.col("c") == 1), F.count_if(F.col("c") == 2)).first()
    total, distinct, customers, once, twice = (int(x) for x in of)
    pairs = told.agg(F.coalesce(F.sum("once"), F.lit(0)), F.coalesce(F.sum("twice"), F.lit(0))).first()
    discount = _discount(*(int(x) for x in pairs))
    law = store(word_law(types, sampled(types, customers, _discount(once, twice))), "word-law")
    further = None
    for sweep in range(context_sweeps):
        known = store(word_answers(asks, law), "word-answers")
        _freed(docs.sparkSession, law, further)
        further = store(further_tables(held, told, known, parts, word_parts, bits, discount, sweep), "further")
        _freed(docs.sparkSession, known, told if sweep == context_sweeps - 1 else None)
        seats = store(with_further(types, further), "seats")
        of = seats.agg(F.coalesce(F.sum("c"), F.lit(0)), F.count_if(F.col("c") == 1), F.count_if(F.col("c") == 2)).first()
        _freed(docs.sparkSession)
        law = store(word_law(seats, sampled(seats, int(of[0]), _discount(int(of[1]), int(of[2])))), "word-law")
        _freed(docs.sparkSession, seats)
    floor = math.log10(total + 0.5 * (distinct + 1))

    def run(row, answers):
        import pyarrow as pa

        b = Block(row, parts, word_parts, bits, not context_sweeps)
        if context_sweeps:
            pair_n, seats_of = (x.astype(np.int64) for x in _answered(answers, 0, 2))
        else:
            pair_n = np.empty(len(b.u), np.int64)
            pair_n[b.pair_order] = _answered(answers, 0, 2)[0]
            seats_of = (pair_n > 0).astype(np.float64)
            del b.hash, b.times, b.pair_part, b.pair_order  # not needed from here on, tens of MB
        n, followers, p = _word_columns(b, answers, 1)
        logp = np.log10(predictive(pair_n, seats_of, n[b.u], followers[b.u], p[b.w], discount))[b.pair]
        start = np.concatenate([[0], np.cumsum(b.n_tokens)[:-1]])
        total_of = lambda x: np.add.reduceat(x, start)
        return pa.table({
            "doc_id": pa.array(b.doc_id, pa.int64()), "held_out": pa.array(b.held_out), "n_tokens": pa.array(b.n_tokens), "n_known": pa.array(total_of((n[b.ids] > 0).astype(np.int64))),
            "train_tokens": pa.array(np.full(len(start), total)), "base_score": pa.array(total_of(np.log10(n + 0.5)[b.ids] - floor)), "score": pa.array(total_of(logp)),
        })

    mine = held.select("block", "doc_id", "held_out", "n_tokens", "ids", "words", "train")
    theirs = _told(further.filter("part < 0") if context_sweeps else told, word_answers(asks, law))
    schema = "doc_id long, held_out boolean, n_tokens long, n_known long, train_tokens long, base_score double, score double"
    return mine.groupBy("block").cogroup(theirs.groupBy("to")).applyInArrow(run, schema)


def predictive(pair_n, tables, context_n, followers, p, discount: float):
    """Probability of a word after a context: ``pair_n`` of its ``context_n`` customers sit at the word's ``tables``, ``followers`` tables stand there, p is the parent's."""
    return (np.maximum(pair_n - discount * tables, 0) + (CONTEXT_STRENGTH + discount * followers) * p) / (CONTEXT_STRENGTH + context_n)


def perplexity(scores: DataFrame) -> DataFrame:
    """Perplexity a token of held-out and training texts: held_out, n_tokens, perplexity, base_perplexity."""
    power = lambda c: F.pow(F.lit(10.0), -F.sum(c) / F.sum("n_tokens"))
    return scores.groupBy("held_out").agg(F.sum("n_tokens").alias("n_tokens"), power("score").alias("perplexity"), power("base_score").alias("base_perplexity"))


def query(spark, sf_dir):
    return language_scores(table(spark, sf_dir, "documents", "doc_id", "text"), CONTEXT_SWEEPS)


def base_query(spark, sf_dir):
    """The columns of the query that the model takes no part in."""
    out = query(spark, sf_dir)
    return out.withColumn("base_score", F.round("base_score", 6)).drop("score")


BASE_SQL = f"""
WITH {CRC_TABLE},
d AS (SELECT doc_id, list_append(list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{BLANK}'), lambda x: x <> ''), '') AS w, {crc_sql("coalesce(CAST(doc_id AS VARCHAR), '')")} % 5 = 1 AS held_out FROM documents, tab),
t AS (SELECT doc_id, held_out, unnest(w) AS token FROM d),
c AS (SELECT token, count(*) AS c FROM t WHERE NOT held_out GROUP BY token),
k AS (SELECT sum(c) AS n, count(*) AS v FROM c)
SELECT doc_id, held_out, CAST(count(*) AS BIGINT) AS n_tokens, CAST(count(c.c) AS BIGINT) AS n_known, CAST(any_value(n) AS BIGINT) AS train_tokens, round(sum(log10((coalesce(c.c, 0) + 0.5) / (n + 0.5 * (v + 1)))), 6) AS base_score
FROM t LEFT JOIN c USING (token), k GROUP BY doc_id, held_out
"""
