"""Near duplicates by one-permutation MinHash with optimal densification, banded buckets and star-shaped candidates.

Sets are the distinct five-word shingles of a text. One hash of each shingle fills ``BINS`` bins (its high part chooses
the bin, the least hash stays); an empty bin takes the value of the first filled bin on a probe path of its own, which
keeps the collision law of MinHash. Bands of ``ROWS`` bins are bucket keys. Texts with equal sets are one class from the
start; classes, not rows, go into the buckets.

In a bucket, every class is paired with one centre only, the class that meets most others, so a bucket of m classes gives
m - 1 pairs. Pairs whose signatures agree too little to be links (see ``SCREEN``) are dropped, and the rest is confirmed on
full sets. A star can miss a link between two members that both differ from its centre. So buckets that still hold several
components are joined into clusters of classes that meet, clusters are dealt into tiles of bounded size, and two tiles at
a time are compared on full sets by an inverted list; only links between components leave a task, one for two components.
After that no two classes that share a bucket are unchecked. A link with similarity 0.75 shares no bucket with chance
(1 - 0.75**6)**64 < 4e-6.

Links are found between classes, which have ids of their own, so doc_ids may be null or stand on several texts: each row
belongs to its own text's class. The centre of a star is joined to its members in parts of at most ``PART`` of them, so
neither a large star nor a large bucket is one task's work, and the centre's text travels once for each part.

Components are smallest-label propagation with pointer jumping, in tables of the shared folder; a component is named by
the smallest doc_id in it, null if no row of it has one. Null, empty and blank texts have no shingles and stay alone; a
text of fewer than five words is one shingle; repeated rows give a row each. kept is doc_id = component_id (null ids
count as equal to a null name). An empty table gives an empty result. Columns other than doc_id and text are ignored.
"""

from __future__ import annotations

import numpy as np
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import BLANK, LOWER, UPPER, few, store, table, text_key, without_rows

SHINGLE = 5
BINS, BANDS = 384, 64
ROWS = BINS // BANDS
#: Links have 100 * shared >= LINK * united.
LINK = 75
#: A pair is dropped unchecked when fewer than this share of bins agree: the spread of the share at similarity 0.75 is
#: sqrt(0.75 * 0.25 / 384) = 0.022, so the limit lies 6.8 deviations below.
SCREEN = 0.60
#: Sets and shingles of a tile, about.
TILE_SETS, TILE_SHINGLES = 1000, 1_000_000
#: Members of a star or bucket that meet their centre in one group.
PART = 64
SIGNED = "doc_id long, text_hash long, text_crc long, n_shingles long, set_hi long, set_lo long, bands array<long>, signature binary"

_U = np.uint64
_B = 0x9E3779B97F4A7C15 | 1
_rng = np.random.default_rng(20240229)
_BYTE = _rng.integers(1, 2**63, 256, dtype=np.int64).astype(_U)
_ODD = (_rng.integers(1, 2**62, SHINGLE, dtype=np.int64).astype(_U) << _U(1)) | _U(1)
#: Row e: the order in which empty bin e asks the other bins; RANK[e, b] is bin b's place in it.
_PROBE = np.argsort(_rng.random((BINS, BINS)), axis=1).astype(np.int64)
_RANK = np.argsort(_PROBE, axis=1).astype(np.int64)
_BAND = (_rng.integers(1, 2**62, ROWS, dtype=np.int64).astype(_U) << _U(1)) | _U(1)


def _mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> _U(30))
    x = x * _U(0xBF58476D1CE4E5B9)
    x = x ^ (x >> _U(27))
    x = x * _U(0x94D049BB133111EB)
    return x ^ (x >> _U(31))


_POWER = np.ones((2, 1), _U)


def _powers(n: int) -> np.ndarray:
    """Powers of the base and of its inverse modulo 2**64, n of each at least."""
    global _POWER
    if _POWER.shape[1] < n:
        out = np.empty((2, max(2 * n, 1 << 16)), _U)
        out[0], out[1] = _U(_B), _U(pow(_B, -1, 1 << 64))
        out[:, 0] = 1
        _POWER = np.multiply.accumulate(out, axis=1)
    return _POWER


def word_hashes(text: bytes) -> np.ndarray:
    """64-bit hashes of the lower-cased words between ASCII white space."""
    raw = np.frombuffer(text.lower(), np.uint8)
    if not len(raw):
        return np.zeros(0, _U)
    blank = ((raw >= 9) & (raw <= 13)) | (raw == 32)
    edge = np.flatnonzero(np.diff(blank.astype(np.int8), prepend=1, append=1))
    begin, end = edge[0::2], edge[1::2]
    # one running sum of byte values times rising powers; a word's part of it, brought down by the power of its start
    power = _powers(len(raw) + 1)
    total = np.zeros(len(raw) + 1, _U)
    np.cumsum(_BYTE[raw] * power[0, : len(raw)], out=total[1:])
    return _mix((total[end] - total[begin]) * power[1, begin] + (end - begin).astype(_U))


def shingle_set(text: bytes) -> np.ndarray:
    """Sorted distinct hashes of the five-word shingles."""
    w = word_hashes(text)
    n = len(w)
    if not n:
        return w
    if n < SHINGLE:
        out = np.zeros(1, _U)
        for k in range(n):
            out = _mix(out + w[k : k + 1] * _ODD[k] + _U(n))
        return out
    out = w[: n - SHINGLE + 1] * _ODD[0]
    for k in range(1, SHINGLE):
        out = out + w[k : n - SHINGLE + 1 + k] * _ODD[k]
    return np.unique(_mix(out))


def signature(s: np.ndarray) -> np.ndarray:
    """Densified bins (uint64) of a sorted, non-empty set of hashes."""
    where = ((s >> _U(32)) * _U(BINS)) >> _U(32)
    first = np.flatnonzero(np.diff(where, prepend=_U(BINS)))
    filled, least = where[first].astype(np.int64), s[first]
    bins = np.zeros(BINS, _U)
    bins[filled] = least
    if len(filled) == BINS:
        return bins
    full = np.zeros(BINS, bool)
    full[filled] = True
    empty = np.flatnonzero(~full)
    if len(filled) <= 48:
        bins[empty] = least[np.argmin(_RANK[empty][:, filled], axis=1)]
        return bins
    take, todo = np.zeros(BINS, np.int64), empty
    for step in range(BINS):
        asked = _PROBE[todo, step]
        met = full[asked]
        take[todo[met]] = asked[met]
        todo = todo[~met]
        if not len(todo):
            break
    bins[empty] = bins[take[empty]]
    return bins


def signed(docs: DataFrame) -> DataFrame:
    """doc_id, text_hash, text_crc, n_shingles, 128 bits that identify the set, band keys, one byte of each bin; bands and signature null without shingles."""

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            rows = [[], [], [], [], []]
            for text in batch.column(3).cast(pa.binary()):
                s = shingle_set(text.as_py() or b"")
                if len(s):
                    bins = signature(s)
                    keys = (_mix(bins.reshape(BANDS, ROWS)) * _BAND).sum(axis=1, dtype=_U) + np.arange(BANDS, dtype=_U)
                    hi, lo = int(_mix(s).sum(dtype=_U).astype(np.int64)), int(np.bitwise_xor.reduce(_mix(s + _U(_B))).astype(np.int64))
                    found = (len(s), hi, lo, _mix(keys).astype(np.int64), (_mix(bins) & _U(255)).astype(np.uint8).tobytes())
                else:
                    found = (0, 0, 0, None, None)
                for c, v in zip(rows, found):
                    c.append(v)
            kinds = [pa.int64()] * 3 + [pa.list_(pa.int64()), pa.binary()]
            yield pa.RecordBatch.from_arrays([*[batch.column(k) for k in range(3)], *[pa.array(c, k) for c, k in zip(rows, kinds)]], names=["doc_id", "text_hash", "text_crc", "n_shingles", "set_hi", "set_lo", "bands", "signature"])

    return docs.select(F.col("doc_id").cast("long"), *text_key(), "text").mapInArrow(run, SIGNED)


def _parted(stars: DataFrame) -> DataFrame:
    """Pairs (hub, rep) with ``part``: members of a star are dealt into parts of about PART, so that no hub is a hot key."""
    large = stars.groupBy("hub").agg(F.count(F.lit(1)).alias("size")).filter(F.col("size") > PART)
    sized = stars.join(few(store(large, "large-stars")), "hub", "left")
    parts = F.coalesce(F.ceil(F.col("size") / PART), F.lit(1))
    return sized.select("hub", "rep", F.pmod(F.xxhash64("rep"), parts).cast("int").alias("part"))


def _close(stars: DataFrame, known: DataFrame) -> DataFrame:
    """Pairs (hub, rep) that may be links: enough bins agree, by one byte of each. known: rep, signature."""
    parted = store(_parted(stars), "parted")
    hubs = parted.select("hub", "part").distinct().join(known.select(F.col("rep").alias("hub"), F.col("signature").alias("of_hub")), "hub")
    both = parted.join(known, "rep").join(hubs, ["hub", "part"])

    def run(batches):
        import pyarrow as pa

        for batch in batches:
            if batch.num_rows:
                one, two = (np.frombuffer(b"".join(batch.column(k).to_pylist()), np.uint8).reshape(-1, BINS) for k in (2, 3))
                mask = pa.array((one == two).sum(axis=1) >= SCREEN * BINS)
                yield pa.RecordBatch.from_arrays([batch.column(k).filter(mask) for k in (0, 1)], names=["hub", "rep"])

    return both.select("hub", "rep", "signature", "of_hub").mapInArrow(run, "hub long, rep long")


def _fits(n: Column, m: Column) -> Column:
    """Set sizes alone allow a link."""
    return 100 * F.least(n, m) >= LINK * F.greatest(n, m)


def _confirmed(close: DataFrame, texts: DataFrame) -> DataFrame:
    """Links (a, b) among pairs (hub, rep): their full sets are compared, part by part of each star. texts: rep, text."""
    parted = store(_parted(close), "parted")
    members = parted.join(texts, "rep").select("hub", "part", "rep", "text")
    hubs = parted.select("hub", "part").distinct().join(texts.select(F.col("rep").alias("hub"), "text"), "hub").select(F.col("hub").alias("centre"), F.col("part").alias("piece"), F.col("text").alias("of_centre"))

    def run(mine, centre):
        import pyarrow as pa

        hub, linked = mine["hub"][0].as_py(), []
        of_hub = shingle_set(centre["of_centre"].cast(pa.binary())[0].as_py() or b"")
        for rep, text in zip(mine["rep"].to_pylist(), mine["text"].cast(pa.binary())):
            other = shingle_set(text.as_py() or b"")
            both = len(of_hub) + len(other) - len(np.union1d(of_hub, other))
            if 100 * both >= LINK * (len(of_hub) + len(other) - both):
                linked.append(rep)
        return pa.table({"a": pa.array([min(hub, r) for r in linked], pa.int64()), "b": pa.array([max(hub, r) for r in linked], pa.int64())})

    return members.groupBy("hub", "part").cogroup(hubs.groupBy("centre", "piece")).applyInArrow(run, "a long, b long")


def components(links: DataFrame, name: str = "component") -> DataFrame:
    """(id, label) for every id in ``links`` (a, b): the smallest id that can be reached.

    Each round gives an id the smallest label around it and the label of that label, and then links labels instead of ids;
    links inside a label vanish, so the graph shrinks fast and rounds are few."""
    ordered = lambda df: df.select(F.least("a", "b").alias("a"), F.greatest("a", "b").alias("b")).filter("a <> b").distinct()
    edges, out, step = store(ordered(links), f"{name}-edges"), None, 0
    while out is None or not edges.isEmpty():
        step += 1
        both = edges.union(edges.select("b", "a"))
        low = store(both.groupBy(F.col("a").alias("id")).agg(F.least(F.min("b"), F.col("id")).alias("low")), f"{name}-low")
        jump = low.select(F.col("id").alias("low"), F.col("low").alias("lower"))
        labels = store(low.join(jump, "low", "left").select("id", F.coalesce("lower", "low").alias("label")), f"{name}-{step}")
        moved = edges.join(labels.select(F.col("id").alias("a"), F.col("label").alias("la")), "a").join(labels.select(F.col("id").alias("b"), F.col("label").alias("lb")), "b")
        edges = store(ordered(moved.select(F.col("la").alias("a"), F.col("lb").alias("b"))), f"{name}-edges")
        if out is None:
            out = labels
        else:
            later = labels.select(F.col("id").alias("label"), F.col("label").alias("later"))
            out = store(out.join(later, "label", "left").select("id", F.coalesce("later", "label").alias("label")), f"{name}-all")
    return out


def _tile_links(members: DataFrame, texts: DataFrame) -> DataFrame:
    """Pairs (a, b) of labels that a link between two members (rep, n, label, cluster) of one cluster joins.

    A cluster is dealt into tiles of bounded shingles, and a task compares two tiles by an inverted list of their shingles."""
    tiles = members.groupBy("cluster").agg(F.greatest(F.ceil(F.count(F.lit(1)) / TILE_SETS), F.ceil(F.sum("n") / TILE_SHINGLES)).cast("int").alias("tiles"))
    dealt = members.join(tiles, "cluster").withColumn("tile", F.pmod(F.xxhash64("rep"), F.col("tiles")).cast("int"))
    dealt = dealt.join(texts, "rep")
    other = F.explode(F.sequence(F.lit(0), F.col("tiles") - 1)).alias("other")
    dealt = dealt.select("cluster", "rep", "label", "text", "tile", other).select("cluster", "label", "text", "tile", F.least("tile", "other").alias("i"), F.greatest("tile", "other").alias("j"))

    def run(group):
        import pyarrow as pa

        group = group.combine_chunks()
        label, tile = (group[c].to_numpy() for c in ("label", "tile"))
        sets = [shingle_set(t.as_py() or b"") for t in group["text"].cast(pa.binary())]
        size = np.array([len(x) for x in sets])
        _, shingle, df = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
        owner, order = np.repeat(np.arange(len(sets)), size), np.argsort(shingle, kind="stable")
        begin, held = np.concatenate([[0], np.cumsum(df)]), owner[order]
        bounds, met = np.concatenate([[0], np.cumsum(size)]), {}
        same = group["i"][0].as_py() == group["j"][0].as_py()
        for k in range(len(sets)):
            mine = shingle[bounds[k] : bounds[k + 1]]
            mine = mine[df[mine] > 1]
            n = df[mine]
            at = np.arange(n.sum()) - np.repeat(np.cumsum(n) - n, n) + np.repeat(begin[mine], n)
            shared = np.bincount(held[at], minlength=len(sets))
            close = np.flatnonzero((100 * shared >= LINK * (size + size[k] - shared)) & (label != label[k]) & (same | (tile != tile[k])))
            for o in close:
                met[(min(label[k], label[o]), max(label[k], label[o]))] = True
        found = list(met)
        return pa.table({"a": pa.array([int(x) for x, _ in found], pa.int64()), "b": pa.array([int(y) for _, y in found], pa.int64())})

    return dealt.groupBy("cluster", "i", "j").applyInArrow(run, "a long, b long")


def _to_bucket(members: DataFrame, of_key: DataFrame) -> DataFrame:
    """``members`` (key, m, rep, ...) with the columns of ``of_key`` (key, m, ...), one row for each key; large buckets meet it in parts of about PART * 8 members."""
    parts = F.ceil(F.col("m") / (8 * PART)).cast("int")
    dealt = members.withColumn("part", F.pmod(F.xxhash64("rep"), parts).cast("int"))
    copies = of_key.withColumn("part", F.explode(F.sequence(F.lit(0), parts - 1))).drop("m")
    return dealt.join(copies, ["key", "part"]).drop("part")


def labelled(docs: DataFrame) -> DataFrame:
    """near_duplicates with text_hash and text_crc, which tell the rows of one doc_id apart, and an id of the component that is there without doc_ids too."""
    rows = store(signed(docs).withColumn("row_key", F.monotonically_increasing_id()), "signed")
    key = ["n_shingles", "set_hi", "set_lo"]
    # classes of equal sets, named by a row of theirs; the hot ones are added up before they are shuffled
    members = rows.filter("n_shingles > 0").select("doc_id", "row_key", "text_hash", "text_crc", *key)
    first = F.min(F.struct("row_key", "text_hash", "text_crc")).alias("first")
    classes = store(members.groupBy(*key).agg(first, F.min("doc_id").alias("least")).select(*key, F.col("first.row_key").alias("rep"), F.col("first.text_hash").alias("text_hash"), F.col("first.text_crc").alias("text_crc"), "least"), "classes")
    # one row for a class: its bands and signature come from its first row
    reps = rows.withColumnRenamed("row_key", "rep").join(few(classes.select("rep")), "rep").select("rep", F.col("n_shingles").alias("n"), "bands", "signature")
    entries = reps.select("rep", "n", F.explode("bands").alias("key"))
    crowded = store(entries.groupBy("key").agg(F.count(F.lit(1)).alias("m")).filter("m > 1"), "crowded")
    buckets = store(entries.join(few(crowded), "key"), "buckets")
    # the centre of a star: the class that meets most others, which is the likeliest to be linked to them
    degree = buckets.groupBy("rep").agg(F.sum("m").alias("degree"))
    hubs = buckets.join(degree, "rep").groupBy("key").agg(F.max("m").alias("m"), F.max(F.struct("degree", (-F.col("rep")).alias("low"), "n")).alias("top"))
    hubs = hubs.select("key", "m", (-F.col("top.low")).alias("hub"), F.col("top.n").alias("hub_n"))
    starred = store(_to_bucket(buckets, hubs), "starred")

    def texts_of(needed: DataFrame) -> DataFrame:
        """rep, text of the classes in ``needed`` (rep): texts that are not needed are left out before anything is shuffled."""
        wanted = store(classes.select("rep", "text_hash", "text_crc").join(few(store(needed.distinct(), "needed")), "rep", "left_semi"), "wanted")
        found = docs.select(*text_key(), "text").join(few(wanted), ["text_hash", "text_crc"])
        return found.select("rep", "text").dropDuplicates(["rep"])

    ends = lambda pairs: pairs.select(F.col("hub").alias("rep")).union(pairs.select("rep"))
    star = store(starred.filter((F.col("rep") != F.col("hub")) & _fits(F.col("n"), F.col("hub_n"))).select("hub", "rep").distinct(), "star")
    known = reps.select("rep", "signature").join(few(store(ends(star).distinct(), "ends")), "rep", "left_semi")
    close = store(_close(star, known), "close")
    links = store(_confirmed(close, texts_of(ends(close))), "links")
    label = components(links, "first")
    # what stars can miss: buckets of three or more that still hold several components
    wide = starred.filter("m > 2").select("key", "m", "rep", "n").join(label.select(F.col("id").alias("rep"), "label"), "rep", "left").withColumn("label", F.coalesce("label", "rep"))
    mixed = wide.groupBy("key").agg(F.max("m").alias("m"), F.min("label").alias("lowest"), F.max("label").alias("highest")).filter("lowest <> highest").select("key", "m", "lowest")
    open_ = store(_to_bucket(wide, mixed), "open")
    if not open_.isEmpty():
        # components that meet in a bucket are one cluster: links between labels, not between ids
        clusters = components(open_.select(F.col("lowest").alias("a"), F.col("label").alias("b")), "cluster")
        inside = open_.select("rep", "n", "label").distinct().join(clusters.select(F.col("id").alias("label"), F.col("label").alias("cluster")), "label")
        found = store(_tile_links(inside, texts_of(inside.select("rep"))), "tile-links")
        if not found.isEmpty():
            # found links name the labels that they join
            later = components(found, "second").select(F.col("id").alias("label"), F.col("label").alias("later"))
            alone = later.select(F.col("label").alias("id")).join(label.select("id"), "id", "left_anti")
            label = label.union(alone.select("id", F.col("id").alias("label")))
            label = label.join(later, "label", "left").select("id", F.coalesce("later", "label").alias("label"))
    # a component's name: the least doc_id of its classes
    joined = store(label.select(F.col("id").alias("rep"), "label").join(classes.select("rep", "least"), "rep"), "labels")
    names = joined.select("rep", "label").join(joined.groupBy("label").agg(F.min("least").alias("name")), "label").select("rep", "label", "name")
    one = F.col("label").isNull()
    named = classes.select(*key, "rep", "least").join(names, "rep", "left").select(*key, F.coalesce("label", "rep").alias("component"), F.when(one, F.col("least")).otherwise(F.col("name")).alias("component_id"))
    linked = members.join(named, key).select("doc_id", "text_hash", "text_crc", "n_shingles", "component", "component_id")
    alone = rows.filter("n_shingles = 0").select("doc_id", "text_hash", "text_crc", "n_shingles", F.lit(None).cast("long").alias("component"), F.col("doc_id").alias("component_id"))
    return linked.union(alone).withColumn("kept", F.col("doc_id").eqNullSafe(F.col("component_id")))


def near_duplicates(docs: DataFrame) -> DataFrame:
    """doc_id, n_shingles, component_id, kept for each row of ``docs`` (doc_id, text)."""
    return labelled(docs).select("doc_id", "n_shingles", "component_id", "kept")


def without_copies(docs: DataFrame) -> DataFrame:
    """The rows of ``docs``, with the caller's columns alone, without near copies: of each component one row stays.

    It is the row with the least doc_id (rows with an id before those without), then the least hash of its text; of equal
    rows any one. Rows without shingles stay."""
    found = store(labelled(docs.select("doc_id", "text")).filter("n_shingles > 0").select("component", "doc_id", "text_hash", "text_crc"), "labelled")
    row = ["doc_id", "text_hash", "text_crc"]
    order = F.struct(F.col("doc_id").isNull().alias("last"), *row)
    stays = found.groupBy("component").agg(F.min(order).alias("s")).select("s.doc_id", "s.text_hash", "s.text_crc", F.lit(True).alias("stays"))
    counts = found.groupBy(*row).agg(F.count(F.lit(1)).alias("rows")).alias("c")
    s = stays.alias("s")
    same = F.col("c.doc_id").eqNullSafe(F.col("s.doc_id")) & (F.col("c.text_hash") == F.col("s.text_hash")) & (F.col("c.text_crc") == F.col("s.text_crc"))
    told = store(counts.join(s, same, "left").select(*[F.col(f"c.{c}") for c in row], "rows", F.coalesce("stays", F.lit(False)).alias("stays")), "told")
    return without_rows(docs, told.filter("not stays").select(*row), told.filter("stays and rows > 1").select(*row))


_WORDS = rf"list_filter(string_split_regex(translate(coalesce(text, ''), '{UPPER}', '{LOWER}'), '{BLANK}'), lambda x: x <> '')"
ORACLE_SQL = f"""
WITH RECURSIVE d AS (SELECT doc_id, {_WORDS} AS w FROM documents),
s AS (SELECT DISTINCT doc_id, unnest(CASE WHEN len(w) >= {SHINGLE} THEN list_transform(range(1, len(w) - {SHINGLE - 2}), lambda i: array_to_string(w[i:i + {SHINGLE - 1}], ' '))
  WHEN len(w) > 0 THEN [array_to_string(w, ' ')] ELSE [] END) AS g FROM d),
n AS (SELECT doc_id, count(*) AS n FROM s GROUP BY 1),
p AS (SELECT a.doc_id AS x, b.doc_id AS y, count(*) AS c FROM s a JOIN s b ON a.g = b.g AND a.doc_id <> b.doc_id GROUP BY 1, 2),
l AS (SELECT x, y FROM p JOIN n a ON a.doc_id = x JOIN n b ON b.doc_id = y WHERE 100 * c >= {LINK} * (a.n + b.n - c)),
r(x, y) AS (SELECT doc_id, doc_id FROM d UNION SELECT r.x, l.y FROM r JOIN l ON r.y = l.x)
SELECT d.doc_id, CAST(coalesce(max(n.n), 0) AS BIGINT) AS n_shingles, CAST(min(r.y) AS BIGINT) AS component_id, d.doc_id = min(r.y) AS kept
FROM d JOIN r ON r.x = d.doc_id LEFT JOIN n ON n.doc_id = d.doc_id GROUP BY d.doc_id
"""


def query(spark, sf_dir):
    return near_duplicates(table(spark, sf_dir, "documents", "doc_id", "text"))
