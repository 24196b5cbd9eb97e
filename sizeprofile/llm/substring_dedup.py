"""Exact removal of repeated passages by a Burrows-Wheeler transform with threshold-bounded interval expansion.

A passage is a string of `length` bytes. Which strings are repeated is found in three steps.

* Anchors. Each `length`-byte window picks one of its GRAM-byte grams by content (the one with the smallest hash, grams
  known to be very frequent last). Equal windows pick equal grams, so they meet under the same key. A run of windows
  that pick the same gram is a context: the bytes they cover. Keys seen once hold no repetition and drop out.
* Equal contexts. A context seen twice is repeated as a whole, wherever it occurs; one copy of it goes on.
* Different contexts under one key. Their bytes are joined into blocks; a suffix array sorted to 256 bytes gives the
  transform, and breadth-first backward extension of intervals derives common prefixes by increasing length up to
  `length`. Boundaries never reached belong to suffixes that agree on `length` bytes at least.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import batches_of, bitmap_of, in_bitmap, mapped, mixed64, release_held, texts_of, written

LENGTH, GRAM = 200, 64
#: Bytes of text handled at once when anchors are picked, and bytes of contexts in one transform.
CHUNK_BYTES, BLOCK_BYTES = 1 << 20, 256 << 10
#: Grams more frequent than HOT_COUNT (or one in HOT_KEYS of all) are picked last; at most HOT_KEYS of them are known.
HOT_COUNT, HOT_KEYS = 500, 100_000
#: Contexts that stand in one in HOT_GROUPS of all places, so fewer than that many, are constants of a filter instead of being joined.
HOT_GROUPS = 1_000
_ODD = [int(x) | 1 for x in mixed64(np.arange(11, 19, dtype=np.uint64))]
_LETTERS = mixed64(np.arange(1, 257, dtype=np.uint64))


def gram_hashes(codes: np.ndarray) -> np.ndarray:
    """64-bit hashes of all GRAM-byte grams (a power of two), by doubling."""
    h, size, k = _LETTERS[codes], 1, 0
    while size < GRAM:
        h = h[:-size] * np.uint64(_ODD[k]) + h[size:]
        size, k = 2 * size, k + 1
    return mixed64(h)


class HotGrams:
    """Membership in a bounded set of hashes: a bitmap first, then the sorted set."""

    def __init__(self, hashes: np.ndarray):
        self.sorted = np.sort(hashes.astype(np.uint64))
        self.bitmap = np.zeros(1 << 20, dtype=bool)
        self.bitmap[(self.sorted & np.uint64((1 << 20) - 1)).astype(np.int64)] = True

    def of(self, h: np.ndarray) -> np.ndarray:
        out = np.zeros(len(h), dtype=bool)
        if len(self.sorted):
            maybe = np.flatnonzero(self.bitmap[(h & np.uint64((1 << 20) - 1)).astype(np.int64)])
            at = np.minimum(np.searchsorted(self.sorted, h[maybe]), len(self.sorted) - 1)
            out[maybe] = self.sorted[at] == h[maybe]
        return out


def contexts(texts: list[bytes], length: int, hot: HotGrams):
    """(which text, key, first window, last window) arrays of all contexts; the texts are taken chunk by chunk."""
    group: list[tuple[int, int, bytes]] = []
    held = 0
    for k, raw in enumerate(texts):
        for at in range(0, max(0, len(raw) - length + 1), CHUNK_BYTES):
            part = raw[at : at + CHUNK_BYTES + length - 1]
            if held and held + len(part) > CHUNK_BYTES:
                yield _contexts(group, length, hot)
                group, held = [], 0
            group.append((k, at, part))
            held += len(part)
    if group:
        yield _contexts(group, length, hot)


def _contexts(group: list[tuple[int, int, bytes]], length: int, hot: HotGrams):
    codes = np.frombuffer(b"".join(p for _, _, p in group), dtype=np.uint8)
    sizes = np.array([len(p) for _, _, p in group])
    begin = np.cumsum(sizes) - sizes
    h = gram_hashes(codes)
    low = np.uint64((1 << 22) - 1)
    best = (h >> np.uint64(1)) & ~low
    best |= np.arange(len(h), dtype=np.uint64)
    if len(hot.sorted):
        best[hot.of(h)] |= np.uint64(1 << 63)
    wide, size = length - GRAM + 1, 1
    while 2 * size <= wide:
        best = np.minimum(best[:-size], best[size:])
        size *= 2
    if wide > size:
        best = np.minimum(best[: len(best) - (wide - size)], best[wide - size :])
    pick = (best & low).astype(np.int64)  # gram picked by the window at each place; windows across texts are cut out below
    first = np.repeat(begin, sizes - length + 1)
    starts = first + np.arange(len(first)) - np.repeat(np.cumsum(sizes - length + 1) - (sizes - length + 1), sizes - length + 1)
    chosen = pick[starts]
    new = np.flatnonzero(np.r_[True, (chosen[1:] != chosen[:-1]) | (first[1:] != first[:-1])])
    last = np.r_[new[1:] - 1, len(starts) - 1]
    owner = np.searchsorted(begin, starts[new], side="right") - 1
    shift = np.array([at for _, at, _ in group])[owner] - begin[owner]
    return np.array([k for k, _, _ in group])[owner], h[chosen[new]].view(np.int64), starts[new] + shift, starts[last] + shift


def repeated_starts(text: bytes, valid: np.ndarray, length: int) -> np.ndarray:
    """Places among `valid` whose `length` bytes also start at another valid place of the text (length up to 256)."""
    n = len(text)
    if not n or not len(valid):
        return np.zeros(0, dtype=np.int64)
    codes = np.frombuffer(text, dtype=np.uint8).astype(np.uint64)
    key = np.zeros(n, dtype=np.uint64)
    for k in range(8):  # rotations are sorted: no end mark is needed, and no valid window runs past the end
        key = key << np.uint64(8) | np.roll(codes, -k)
    order = np.argsort(key, kind="stable")
    ranked = key[order]
    begins = np.r_[True, ranked[1:] != ranked[:-1]]  # first row of each group of rotations not yet told apart
    rank = np.empty(n, dtype=np.int64)
    rank[order] = np.maximum.accumulate(np.where(begins, np.arange(n), 0))
    size = 8
    while size < 256:  # prefix doubling, on groups of two and more only
        rows = np.flatnonzero(~(begins & np.r_[begins[1:], True]))
        if not len(rows):
            break
        places = order[rows]
        key = rank[places] * n + rank[(places + size) % n]
        by_key = np.argsort(key, kind="stable")
        places, key = places[by_key], key[by_key]
        order[rows] = places
        begins[rows] = np.r_[True, key[1:] != key[:-1]]
        rank[places] = rows[np.maximum.accumulate(np.where(begins[rows], np.arange(len(rows)), 0))]
        size *= 2
    # the transform, and where each row's letter stands when it comes first
    letter = codes[order - 1].astype(np.int64)
    by_letter = np.argsort(letter, kind="stable")
    moved = np.empty(n, dtype=np.int64)
    moved[by_letter] = np.arange(n)
    same = letter[by_letter[1:]] == letter[by_letter[:-1]]
    following = np.full(n, n, dtype=np.int64)  # next row with the same letter
    following[by_letter[:-1][same]] = by_letter[1:][same]
    preceding = np.full(n, -1, dtype=np.int64)
    preceding[by_letter[1:][same]] = by_letter[:-1][same]
    open_ = np.ones(n + 1, dtype=bool)  # boundary before row r not yet reached: common prefix of at least the present length
    open_[[0, n]] = False
    lo, hi = np.zeros(1, dtype=np.int64), np.full(1, n, dtype=np.int64)
    for _ in range(length):
        if not len(lo):
            break
        width = hi - lo
        ends = np.cumsum(width)
        row = np.arange(ends[-1]) + np.repeat(lo - (ends - width), width)
        low, high = np.repeat(lo, width), np.repeat(hi, width)
        begins = row[preceding[row] < low]
        stops = row[following[row] >= high]
        a, b = np.sort(moved[begins]), np.sort(moved[stops]) + 1  # one interval a letter and interval, disjoint
        fresh = open_[b]
        lo, hi = a[fresh], b[fresh]
        open_[hi] = False
    group = np.cumsum(~open_[:n]) - 1  # rows that agree on `length` bytes
    is_valid = np.zeros(n, dtype=bool)
    is_valid[valid] = True
    count = np.bincount(group, weights=is_valid[order], minlength=1)
    hit = np.zeros(n, dtype=bool)
    hit[order] = count[group] >= 2
    return valid[hit[valid]]


def _runs(x: np.ndarray) -> list[tuple[int, int]]:
    """Maximal runs of consecutive numbers of an ascending array."""
    if not len(x):
        return []
    cut = np.flatnonzero(np.diff(x) != 1)
    return list(zip(x[np.r_[0, cut + 1]].tolist(), x[np.r_[cut, len(x) - 1]].tolist()))


_ROWS = pa.schema([("key", pa.int64()), ("digest", pa.int64()), ("tid", pa.int64()), ("size", pa.int32()), ("span", pa.int64())])
_MARKS = pa.schema([("tid", pa.int64()), ("size", pa.int32()), ("span", pa.int64())])
_PIECES = pa.schema([("key", pa.int64()), ("tid", pa.int64()), ("size", pa.int32()), ("span", pa.int64()), ("piece", pa.binary())])


def _cut(raw: bytes, spans: list[int], length: int) -> tuple[bytes, int, int]:
    """(what is left, bytes removed, maximal removed runs); a span packs the first and last window."""
    if not spans:
        return raw, 0, 0
    first = np.sort(np.array(spans, dtype=np.int64))
    lo, hi = first >> 32, (first & 0xFFFFFFFF) + length
    reach = np.maximum.accumulate(hi)
    new = np.flatnonzero(np.r_[True, lo[1:] > reach[:-1]])
    lo, hi = lo[new], reach[np.r_[new[1:] - 1, len(reach) - 1]]
    kept, at = [], 0
    for a, b in zip(lo.tolist(), hi.tolist()):
        kept.append(raw[at:a])
        at = b
    kept.append(raw[at:])
    return b"".join(kept), int((hi - lo).sum()), len(lo)


def _among(pairs: list[tuple[int, int]]) -> Column:
    """Whether (key, digest) is one of the pairs; most rows are told by the digest alone."""
    if not pairs:
        return F.lit(False)
    return F.col("digest").isin([d for _, d in pairs]) & F.concat_ws(":", "key", "digest").isin([f"{k}:{d}" for k, d in pairs])


def remove_repeated(docs: DataFrame, length: int = LENGTH, text_col: str = "text") -> DataFrame:
    """Cut out of each text every byte that lies in a `length`-byte string which also starts anywhere else.

    Returns the columns of `docs` without the text, plus n_bytes, n_removed, n_spans and kept (binary: what is left may
    split a code point); input columns of these names are replaced. A null text is empty and, like texts of fewer than
    `length` bytes, loses nothing. Repeated rows of `length` bytes or more lose everything. Texts are told apart by a
    64-bit hash and their size, so ids may repeat or be null. `length` is between GRAM + 1 and 256.

    Scale: contexts are fixed-width rows (about one for 85 bytes of text); they are aggregated by key before the join
    that keeps keys seen twice, and a bounded bitmap of those keys leaves most others out of that join. A frequent passage makes frequent grams; picked last, they stand only for windows
    inside the passage, whose contexts are equal and collapse, so no key gathers a context from each document.
    Texts are shuffled once by hash; both joins use that exchange.
    """
    if not GRAM < length <= 256:
        raise ValueError(f"length must be in {GRAM + 1}..256")
    raw = F.coalesce(F.col(f"`{text_col}`"), F.lit(""))
    gone = {"n_bytes", "n_removed", "n_spans", "kept", text_col.lower()}
    others = [c for c in docs.columns if c.lower() not in gone]
    inner = docs.select(F.struct(*[F.col(f"`{c}`") for c in others] or [F.lit(0).alias("none")]).alias("rest"), raw.alias("text"), F.xxhash64(raw).alias("tid"), F.octet_length(raw).alias("size"))
    scanned = inner.select("tid", "size", "text").where(F.col("size") >= length)

    def count_grams(batches):
        release_held()
        for b in batches:
            for _, key, _, _ in contexts(texts_of(b, "text"), length, HotGrams(np.zeros(0, dtype=np.uint64))):
                values, counts = np.unique(key, return_counts=True)
                many = counts > 1  # a frequent gram comes up more than once in some chunks
                yield pa.RecordBatch.from_arrays([pa.array(values[many]), pa.array(counts[many])], names=["key", "n"])
                yield pa.RecordBatch.from_arrays([pa.array([None], type=pa.int64()), pa.array([int(counts.sum())], type=pa.int64())], names=["key", "n"])

    counts = written(scanned.mapInArrow(count_grams, "key long, n long").groupBy("key").agg(F.sum("n").alias("n")), "gram-counts")
    total = counts.where("key is null").agg(F.max("n")).first()[0] or 0
    least = max(HOT_COUNT, total // HOT_KEYS + 1)
    frequent = np.array([r.key for r in counts.where(F.col("key").isNotNull() & (F.col("n") >= least)).select("key").collect()], dtype=np.int64).view(np.uint64)

    def keys_of(batches):
        release_held()
        hot = HotGrams(frequent)
        for b in batches:
            for _, key, _, _ in contexts(texts_of(b, "text"), length, hot):
                values, counts = np.unique(key, return_counts=True)
                yield pa.RecordBatch.from_arrays([pa.array(values), pa.array(counts)], names=["key", "n"])

    # written, as a plain side of the next join: AQE splits the contexts of a hot key
    keys = written(scanned.select("text").mapInArrow(keys_of, "key long, n long").groupBy("key").agg(F.sum("n").alias("n")).where("n > 1").select("key"), "met-keys")
    maybe = bitmap_of(keys, "key")

    def scan(batches):
        release_held()
        hot = HotGrams(frequent)
        for b in batches:
            texts = texts_of(b, "text")
            tid, size = (b.column(k).to_numpy(zero_copy_only=False) for k in (0, 1))
            for who, key, lo, hi in contexts(texts, length, hot):
                known = in_bitmap(maybe, key)
                who, key, lo, hi = who[known], key[known], lo[known], hi[known]
                digest = [hashlib.blake2b(texts[k][x : y + length], digest_size=8).digest() for k, x, y in zip(who.tolist(), lo.tolist(), hi.tolist())]
                yield pa.RecordBatch.from_arrays([pa.array(key), pa.array(np.frombuffer(b"".join(digest), dtype="<i8")), pa.array(tid[who]), pa.array(size[who]), pa.array(lo << 32 | hi)], schema=_ROWS)

    met = written(scanned.mapInArrow(scan, "key long, digest long, tid long, size int, span long").join(keys, "key"), "met-contexts")
    groups = written(met.groupBy("key", "digest").agg(F.count(F.lit(1)).alias("n"), F.min(F.struct("tid", "size", "span")).alias("one")), "context-groups")
    total = groups.agg(F.coalesce(F.sum("n"), F.lit(0))).first()[0]
    hot = F.col("n") > max(1, total // HOT_GROUPS)
    # fewer than HOT_GROUPS rows: constants of a filter, so a context that very many texts hold takes part in no join
    hottest = _among([(r.key, r.digest) for r in groups.where(hot).select("key", "digest").collect()])
    cooler = met.where(~hottest).join(groups.where((F.col("n") > 1) & ~hot).select("key", "digest"), ["key", "digest"])
    whole = met.where(hottest).unionByName(cooler).select("tid", "size", "span")
    several = written(groups.groupBy("key").agg(F.count(F.lit(1)).alias("n")).where("n > 1").select("key"), "mixed-keys")
    mixed = groups.join(several, "key").select("one.*", "key")
    wanted = mixed.groupBy("tid", "size").agg(F.collect_list(F.struct("key", "span")).alias("wanted"))

    def pieces(batches):
        def one():
            seen = None
            for b in batches:
                for tid, size, spans, text in zip(b.column(0).to_pylist(), b.column(1).to_pylist(), b.column(2).to_pylist(), texts_of(b, "text")):
                    if (tid, size) != seen:  # copies of a text follow each other
                        for s in spans:
                            yield s["key"], tid, size, s["span"], text[s["span"] >> 32 : (s["span"] & 0xFFFFFFFF) + length]
                    seen = (tid, size)

        yield from batches_of(_PIECES, one(), weigh=lambda r: len(r[-1]))

    cut = inner.join(wanted, ["tid", "size"]).select("tid", "size", "wanted", "text").mapInArrow(pieces, "key long, tid long, size int, span long, piece binary")
    dealt = cut.dropDuplicates(["key", "tid", "size", "span"]).repartition("key").sortWithinPartitions("key")

    def transform(batches):
        release_held()
        def blocks():
            held, size, last = [], 0, None
            for b in batches:
                for r in zip(*(c.to_pylist() for c in b.columns)):
                    if size >= BLOCK_BYTES and r[0] != last:
                        yield held
                        held, size = [], 0
                    held.append(r)
                    size += len(r[4]) + 1
                    last = r[0]
            if held:
                yield held

        def marks():
            for block in blocks():
                sizes = np.array([len(r[4]) for r in block])
                begin = np.cumsum(sizes + 1) - (sizes + 1)
                many = sizes - length + 1
                valid = np.repeat(begin, many) + np.arange(many.sum()) - np.repeat(np.cumsum(many) - many, many)
                found = repeated_starts(b"\0".join(r[4] for r in block), valid, length)
                owner = np.searchsorted(begin, found, side="right") - 1
                for k in np.unique(owner).tolist():
                    _, tid, size, span, _ = block[k]
                    for a, z in _runs(found[owner == k] - begin[k] + (span >> 32)):
                        yield tid, size, a << 32 | z

        yield from batches_of(_MARKS, marks())

    marks = whole.unionByName(dealt.mapInArrow(transform, "tid long, size int, span long"))
    spans = marks.groupBy("tid", "size").agg(F.collect_set("span").alias("spans"))
    joined = inner.join(spans, ["tid", "size"], "left").select("rest", "text", "spans")

    def kernel():
        def one(batch):
            got = [_cut(t, s or [], length) for t, s in zip(texts_of(batch, "text"), batch.column(batch.schema.get_field_index("spans")).to_pylist())]
            sizes = [len(k) + n for k, n, _ in got]
            return [pa.array(sizes, type=pa.int64()), pa.array([g[1] for g in got], type=pa.int64()), pa.array([g[2] for g in got], type=pa.int64()), pa.array([g[0] for g in got], type=pa.binary())]

        return one

    out = mapped(joined, {"n_bytes": "long", "n_removed": "long", "n_spans": "long", "kept": "binary"}, kernel, drop=("text", "spans"))
    return out.select(*[F.col("rest").getField(c).alias(c) for c in others], "n_bytes", "n_removed", "n_spans", "kept")


def op9_substring_dedup(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    return remove_repeated(docs).select("doc_id", "n_bytes", "n_removed", "n_spans", F.sha2("kept", 256).alias("kept_sha256"))


OP9_SQL = r"""
with h as (select doc_id, hex(encode(coalesce(text, ''))) as x from documents),
n as (select doc_id, x, (length(x) // 2)::bigint as n_bytes from h),
w as (select doc_id, s, md5(substr(x, 2 * s + 1, 400)) as k from (select doc_id, x, unnest(range(0, greatest(n_bytes - 199, 0))) as s from n) t),
hit as (select doc_id, s from w where k in (select k from w group by k having count(*) > 1)),
run as (select doc_id, s, sum(new) over (partition by doc_id order by s rows unbounded preceding) as r
  from (select doc_id, s, case when s - lag(s) over (partition by doc_id order by s) <= 200 then 0 else 1 end as new from hit) t),
span as (select doc_id, r, min(s) as a, max(s) + 200 as b from run group by doc_id, r),
left_over as (
  select n.doc_id, s.r as r, substr(n.x, 2 * coalesce(lag(s.b) over (partition by n.doc_id order by s.a), 0) + 1, 2 * (s.a - coalesce(lag(s.b) over (partition by n.doc_id order by s.a), 0))) as part from n join span s on s.doc_id = n.doc_id
  union all select n.doc_id, 1000000000, substr(n.x, 2 * coalesce(max(s.b), 0) + 1) from n left join span s on s.doc_id = n.doc_id group by n.doc_id, n.x),
kept as (select doc_id, sha256(unhex(string_agg(part, '' order by r))) as kept_sha256 from left_over group by doc_id)
select n.doc_id, n.n_bytes, coalesce(sum(s.b - s.a), 0)::bigint as n_removed, count(s.r) as n_spans, k.kept_sha256
from n left join span s on s.doc_id = n.doc_id join kept k on k.doc_id = n.doc_id group by n.doc_id, n.n_bytes, k.kept_sha256
"""
