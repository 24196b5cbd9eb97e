"""N-gram Jaccard join with adaptive multi-match prefixes, down to components of linked documents.

A document is the set of its distinct word shingles. Under one global order of shingles (those known to be frequent
last), a set's prefix of length n - ceil(t n) + m shares at least m shingles with the prefix of every set of similarity
t or more. Each document picks its m: the longest prefix that it may take is listed, the lengths of the lists that it
meets are measured, and a longer prefix with more required matches is taken where it costs fewer candidates. Two
documents need the smaller of their m.

Equal sets are one node. Shingles that stand in the same documents' prefixes are one list with a weight, so documents
that share a passage or almost all of their text meet a few times, not once a shingle. Before pairs are formed, lists
are linked through a few members (hubs) whose links are verified; lists that lie in one component then need no pairs,
so a large group of near copies costs links in proportion to its size. Pairs across components are then all formed,
counted and verified: no link is lost.
"""

from __future__ import annotations

import hashlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import batches_of, bitmap_of, in_bitmap, lean, mixed64, rows_of, scratch, texts_of, written
from .components import connected_components
from .substring_dedup import _LETTERS

#: Shingles of at least 2**HOT_LEVEL counted copies are ordered by their count; at most HOT_SHINGLES of them.
HOT_LEVEL, HOT_SHINGLES = 5, 200_000
#: Most matches that a document may ask for, against the least; cost of a candidate against that of an entry in a list.
MOST_MATCHES, CANDIDATE_COST = 1.5, 64.0
#: Hub rounds go on while the pairs left fall by this factor at least.
ROUND_GAIN = 0.8
#: Bytes of text shingled at once, and shingles counted at once.
_CHUNK, _COUNTED = 1 << 18, 1 << 22
_BASE = np.uint64(0x9E3779B97F4A7C15)
_ROLES = mixed64(np.arange(301, 306, dtype=np.uint64)) | np.uint64(1)


class Shingler:
    """Distinct shingles of many texts at once, as ascending 64-bit hashes."""

    def __init__(self, width: int = 3):
        self.width = width
        self.space = np.zeros(256, dtype=bool)
        self.space[[9, 10, 11, 12, 13, 32]] = True
        self.powers = self.inverse = np.ones(1, dtype=np.uint64)

    def _grow(self, n: int) -> None:
        if n > len(self.powers):
            n = max(n, 2 * _CHUNK)
            back = np.uint64(pow(int(_BASE), -1, 1 << 64))
            self.powers = np.cumprod(np.r_[np.uint64(1), np.full(n - 1, _BASE)], dtype=np.uint64)
            self.inverse = np.cumprod(np.r_[np.uint64(1), np.full(n - 1, back)], dtype=np.uint64)

    def sets(self, texts: list[bytes]):
        """The set of each text, in order. Texts are taken in chunks of about 256 KB; a longer one is a chunk of its own."""
        part, held = [], 0
        for t in texts:
            if part and held + len(t) > _CHUNK:
                yield from self._sets(part)
                part, held = [], 0
            part.append(t)
            held += len(t) + 1
        if part:
            yield from self._sets(part)

    def _sets(self, texts: list[bytes]):
        raw = np.frombuffer(b" ".join(texts).lower() + b" ", dtype=np.uint8)
        self._grow(len(raw))
        sizes = np.array([len(t) + 1 for t in texts])
        begin = np.cumsum(sizes) - sizes
        gap = self.space[raw]
        before = np.r_[True, gap[:-1]]
        starts, ends = np.flatnonzero(~gap & before), np.flatnonzero(gap & ~before)
        total = np.r_[np.uint64(0), np.cumsum(_LETTERS[raw] * self.powers[: len(raw)], dtype=np.uint64)]
        words = mixed64((total[ends] - total[starts]) * self.inverse[starts] + (ends - starts).astype(np.uint64))
        first = np.searchsorted(starts, begin)
        count = np.r_[first[1:], len(starts)] - first
        w = self.width
        rolled = np.zeros(max(0, len(words) - w + 1), dtype=np.uint64)
        for k in range(w):
            rolled += words[k : k + len(rolled)] * _ROLES[k]
        rolled = mixed64(rolled)
        for a, n in zip(first.tolist(), count.tolist()):
            if n >= w:
                yield np.unique(rolled[a : a + n - w + 1])
            elif n:  # the whole sequence is the one shingle
                short = sum((words[a + k : a + k + 1] * _ROLES[k] for k in range(n)), np.array([n], dtype=np.uint64))
                yield mixed64(short * _ROLES[4])
            else:
                yield np.zeros(0, dtype=np.uint64)


class Repeats:
    """How often hashes come up, for those that come up twice or more among up to `room` of them: a buffer sorted in place."""

    def __init__(self, room: int = _COUNTED):
        self.buffer, self.held = np.empty(room, dtype=np.uint64), 0

    def add(self, s: np.ndarray):
        """Take hashes in; yields (hashes, counts) whenever the buffer is full."""
        while len(s):
            part = s[: len(self.buffer) - self.held]
            self.buffer[self.held : self.held + len(part)] = part
            self.held, s = self.held + len(part), s[len(part) :]
            if self.held == len(self.buffer):
                yield self.flush()

    def flush(self) -> tuple[np.ndarray, np.ndarray]:
        x = self.buffer[: self.held]
        x.sort()
        same = np.r_[False, x[1:] == x[:-1], False]  # whether each hash equals the one before it
        first, last = np.flatnonzero(~same[:-1] & same[1:]), np.flatnonzero(same[:-1] & ~same[1:])
        self.held = 0
        return x[first], last - first + 1


class Order:
    """The global order: by count class (0: not known as frequent), then by hash."""

    def __init__(self, hot: np.ndarray, level: np.ndarray):
        order = np.argsort(hot)
        self.hot, self.level = hot[order], level[order]
        self.bitmap = np.zeros(1 << 20, dtype=bool)
        self.bitmap[(self.hot & np.uint64((1 << 20) - 1)).astype(np.int64)] = True

    def levels(self, s: np.ndarray) -> np.ndarray:
        out = np.zeros(len(s), dtype=np.int64)
        if len(self.hot):
            maybe = np.flatnonzero(self.bitmap[(s & np.uint64((1 << 20) - 1)).astype(np.int64)])
            at = np.minimum(np.searchsorted(self.hot, s[maybe]), len(self.hot) - 1)
            out[maybe] = np.where(self.hot[at] == s[maybe], self.level[at], 0)
        return out

    def prefix(self, s: np.ndarray, percent: int) -> np.ndarray:
        """The longest prefix that the set may take, in the global order."""
        n, order = len(s), np.lexsort((s, self.levels(s)))
        return s[order[: n + (-percent * n // 100) + most_matches(n, percent)]]


def least_matches(n: int, percent: int) -> int:
    """Matches that a set of n shingles asks for at least: a tenth of it, or as many as it may miss.

    So a prefix is at most twice the shortest one, and who shares only a passage with others (its share of a prefix in
    hash order is about its share of the text) falls short of the matches in most cases. Never falls as n grows.
    """
    return max(1, min(n + (-percent * n // 100), n // 10))


def most_matches(n: int, percent: int) -> int:
    """Matches that a set of n shingles may ask for at most: the prefix must fit into the set."""
    return max(least_matches(n, percent), min(int(MOST_MATCHES * least_matches(n, percent)), n * percent // 100))


#: Bits of a set's parity sketch, as 64-bit columns.
SKETCH = tuple(f"p{k}" for k in range(8))


def parities(s: np.ndarray) -> np.ndarray:
    """Whether the number of shingles in each hash class is odd, a class a bit. A class in which two sets differ holds a
    shingle that only one of them has, so differing bits never outnumber the sets' symmetric difference."""
    classes = 64 * len(SKETCH)
    odd = np.bincount(((s >> np.uint64(20)) & np.uint64(classes - 1)).astype(np.int64), minlength=classes) & 1
    return np.packbits(odd.astype(np.uint8), bitorder="little").view("<i8")


def node_of(s: np.ndarray) -> bytes:
    """128-bit identity of a set."""
    return hashlib.blake2b(s.tobytes(), digest_size=16).digest()


_SETS = pa.schema([("node", pa.binary()), ("n", pa.int64()), ("shingles", pa.binary()), *[(p, pa.int64()) for p in SKETCH]])


def _verified(pairs: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """The pairs (a, b) whose sets reach the similarity."""

    def check(batches):
        for b in batches:
            sides = [[np.frombuffer(x, dtype="<u8") for x in b.column(k).to_pylist()] for k in (2, 3)]
            keep = []
            for x, y in zip(*sides):
                both = len(np.intersect1d(x, y, assume_unique=True))
                keep.append(100 * both >= percent * (len(x) + len(y) - both))
            yield pa.RecordBatch.from_arrays([b.column(0), b.column(1)], names=["a", "b"]).filter(pa.array(keep, type=pa.bool_()))

    if 8 * pairs.count() < sets.count():  # few of the sets: only those are shuffled
        asked = pairs.select(F.col("a").alias("node")).unionByName(pairs.select(F.col("b").alias("node"))).distinct()
        sets = sets.join(written(asked, "asked-nodes"), "node", "left_semi")
    left = sets.select(F.col("node").alias("a"), F.col("shingles").alias("x"))
    right = sets.select(F.col("node").alias("b"), F.col("shingles").alias("y"))
    return pairs.join(left, "a").join(right, "b").select("a", "b", "x", "y").mapInArrow(lean(check), "a long, b long")


def jaccard_components(docs: DataFrame, percent: int = 90, width: int = 3, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles and component_id (smallest id reachable by links) of every row of `docs`.

    Words are runs of non-space bytes with A-Z lower-cased; a text of fewer than `width` words is one shingle, and one
    without words (null, empty, white space) has the empty set and is linked with nothing: its component is its own id.
    Two sets link when 100 x intersection >= percent x union. Repeated rows and ids: each row is judged by its own
    text, and rows of equal sets are linked. A null id takes part, but is never the smallest id of a component with a
    known one. Shingles are told apart by 64-bit hashes, sets by 128-bit ones.

    Scale: what is shuffled is a row a document, the prefixes (about a quarter of the shingles, each once a task), the
    entries of only those nodes that share enough prefix shingles with others, and the sets of nodes that stay in a list. Frequent
    shingles are few at any size (HOT_SHINGLES) and go to the tasks. Hub links handle large groups; what is left across
    components is joined from the smaller side. Every aggregate by a key that may be hot is written before it is joined
    back, so that the join has plain sides, which AQE splits.
    """
    with scratch(docs.sparkSession, "prefixes", "node-components"):
        return _components(docs, percent, width, id_col, text_col)


def _components(docs: DataFrame, percent: int, width: int, id_col: str, text_col: str) -> DataFrame:
    rows = rows_of(docs, doc_id=F.col(f"`{id_col}`").cast("long"), text=F.coalesce(F.col(f"`{text_col}`"), F.lit("")))

    def count(batches):
        shingler, repeats = Shingler(width), Repeats()
        for b in batches:
            for s in shingler.sets(texts_of(b, "text")):
                yield from map(of_counts, repeats.add(s))
        yield of_counts(repeats.flush())

    def of_counts(found):
        return pa.RecordBatch.from_arrays([pa.array(found[0].view(np.int64)), pa.array(found[1])], names=["shingle", "n"])

    counted = rows.select("text").mapInArrow(lean(count), "shingle long, n long").groupBy("shingle").agg(F.sum("n").alias("n"))
    counted = written(counted.select("shingle", F.floor(F.log2("n")).cast("int").alias("level")).where(F.col("level") >= HOT_LEVEL), "shingle-levels")
    sizes = sorted(((r.level, r.n) for r in counted.groupBy("level").agg(F.count(F.lit(1)).alias("n")).collect()), reverse=True)
    least, room = 64, HOT_SHINGLES
    for level, n in sizes:
        if n > room:
            break
        least, room = level, room - n
    hot = counted.where(F.col("level") >= least).toArrow()
    hot_keys, hot_levels = hot.column("shingle").to_numpy().view(np.uint64), hot.column("level").to_numpy().astype(np.int64)

    def scan(batches):
        shingler, order = Shingler(width), Order(hot_keys, hot_levels)
        for b in batches:
            node, n, prefix = [], [], []
            for s in shingler.sets(texts_of(b, "text")):
                node.append(node_of(s))
                n.append(len(s))
                prefix.append(order.prefix(s, percent).tobytes())
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(node, type=pa.binary()), pa.array(n, type=pa.int64()), pa.array(prefix, type=pa.binary())], names=["doc_id", "node", "n", "prefix"])

    judged = written(rows.mapInArrow(lean(scan), "doc_id long, node binary, n long, prefix binary"), "prefixes")
    nodes = written(judged.where("n > 0").groupBy("node").agg(F.min("doc_id").alias("doc_id")), "nodes")
    first = bitmap_of(nodes.select(_slot("doc_id")), "doc_id")  # leaves out most copies of a set before their prefixes are listed

    def lists(known: np.ndarray | None):
        """Shingles of the nodes' prefixes; with a bitmap of shared shingles, entries of those nodes only that share enough for any partner."""

        def run(batches):
            for b in batches:
                n = b.column(2).to_numpy(zero_copy_only=False)
                raw = [np.frombuffer(x, dtype="<i8") if f else np.zeros(0, dtype=np.int64) for x, f in zip(b.column(3).to_pylist(), in_bitmap(first, _ids(b.column(0))))]
                at = [np.arange(len(x)) for x in raw]
                if known is not None:
                    for k, x in enumerate(raw):
                        hit = np.flatnonzero(in_bitmap(known, x))
                        at[k] = hit if len(hit) >= least_matches(-(-percent * int(n[k]) // 100), percent) else hit[:0]
                        raw[k] = x[at[k]]
                pick = np.repeat(np.arange(b.num_rows), np.array([len(x) for x in raw], dtype=np.int64))
                if not len(pick):
                    continue
                if known is None:
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(raw))], names=["shingle"])
                else:
                    where = pa.array(pick)
                    yield pa.RecordBatch.from_arrays([pa.array(np.concatenate(raw)), pa.array(np.concatenate(at).astype(np.int32)), *(b.column(k).take(where) for k in (0, 1, 2))], names=["shingle", "pos", "doc_id", "node", "n"])

        return run

    columns = judged.where("n > 0").select("doc_id", "node", "n", "prefix")
    shared = columns.mapInArrow(lean(lists(None)), "shingle long").groupBy("shingle").agg(F.count(F.lit(1)).alias("p")).where("p > 1")
    for _ in range(2):  # nodes that drop out take lists along
        shared = written(shared, "shared-shingles")
        listed = columns.mapInArrow(lean(lists(bitmap_of(shared, "shingle"))), "shingle long, pos int, doc_id long, node binary, n long")
        shared = listed.groupBy("shingle").agg(F.count(F.lit(1)).alias("p")).where("p > 1")
    entries = written(_chosen(listed.join(written(shared, "shared-shingles"), "shingle"), percent), "entries")
    grouped = written(_grouped(entries), "grouped-entries")
    wanted = nodes.join(grouped.groupBy("node").agg((F.sum(F.col("w") * (F.col("p") - 1)) / F.first("n")).alias("score")), "node")
    wanted = written(wanted, "wanted")
    known = bitmap_of(wanted.select(_slot("doc_id")), "doc_id")

    def fetch(batches):
        shingler = Shingler(width)

        def one():
            for b in batches:
                b = b.filter(pa.array(in_bitmap(known, _ids(b.column(0)))))
                for s in shingler.sets(texts_of(b, "text")):
                    yield node_of(s), len(s), s.tobytes(), *parities(s).tolist()

        yield from batches_of(_SETS, one(), weigh=lambda r: len(r[2]))

    fetched = rows.select("doc_id", "text").mapInArrow(lean(fetch), f"node binary, n long, shingles binary, {', '.join(f'{p} long' for p in SKETCH)}")
    # from here on to the components a node is a number of its own, drawn as the table is written
    sets = written(fetched.join(wanted.select("node", "score"), "node").dropDuplicates(["node"]).withColumn("number", F.monotonically_increasing_id()), "sets")
    listed = grouped.select("shingle", "node", "m", "w").join(sets.select("node", "number", "n", "score", *SKETCH), "node")
    listed = written(listed.drop("node").withColumnRenamed("number", "node"), "lists")
    roots = _linked(listed, sets.select(F.col("number").alias("node"), "shingles"), percent)
    roots = written(roots.join(sets.select(F.col("number"), F.col("node").alias("known")), roots.node == F.col("number")).select(F.col("known").alias("node"), "root"), "rooted")
    smallest = written(roots.join(nodes, "node").groupBy("root").agg(F.min("doc_id").alias("component_id")), "smallest")
    labels = written(roots.join(smallest, "root").select("node", "component_id"), "labels")
    by_node = written(nodes.join(labels, "node", "left").select("node", F.coalesce("component_id", "doc_id").alias("component_id")), "node-components")
    out = judged.select("doc_id", "node", "n").join(by_node, "node", "left")
    return out.select("doc_id", F.col("n").alias("n_shingles"), F.when(F.col("n") == 0, F.col("doc_id")).otherwise(F.col("component_id")).alias("component_id"))


def _chosen(listed: DataFrame, percent: int) -> DataFrame:
    """(shingle, node, n, m): each node's prefix for the number of matches m that costs least, by the measured lengths p of the lists.

    A prefix's lists, in total over m, bound the candidates that reach m matches. That sum only grows at an entry, so the
    best m is one that ends right before an entry, or the most. Copies of a node are dropped.
    """
    n = F.col("n")
    base = n - F.ceil(n * percent / 100)
    least = F.greatest(F.lit(1), F.least(base, F.expr("n div 10")))
    most = F.greatest(least, F.least(F.floor(least * MOST_MATCHES), F.floor(n * percent / 100)))
    own = listed.repartition("node").dropDuplicates(["node", "pos"]).withColumn("base", base).withColumn("least", least).withColumn("most", most)
    before = Window.partitionBy("node").orderBy("pos").rowsBetween(Window.unboundedPreceding, -1)
    whole = Window.partitionBy("node")
    cost = lambda lists, m: F.struct((lists * (1 + CANDIDATE_COST / m)).alias("cost"), m.alias("m"))
    own = own.withColumn("before", F.coalesce(F.sum("p").over(before), F.lit(0)))
    ends = F.when(F.col("pos") >= F.col("base") + F.col("least"), cost(F.col("before"), F.col("pos") - F.col("base")))
    best = F.least(F.min(ends).over(whole), cost(F.sum("p").over(whole), F.col("most").cast("long")))
    return own.withColumn("m", best["m"]).where(F.col("pos") < F.col("base") + F.col("m")).select("shingle", "node", "n", F.col("m").cast("int").alias("m"))


def _grouped(entries: DataFrame) -> DataFrame:
    """Entries of one list (the smallest shingle, with the weight w and the length p) for all shingles with the same nodes."""
    nodes = F.bit_xor(F.xxhash64("node")).alias("x"), F.bit_xor(F.xxhash64(F.lit(1), "node")).alias("y")
    lists = entries.groupBy("shingle").agg(F.count(F.lit(1)).alias("p"), *nodes).where("p > 1")
    kept = lists.groupBy("p", "x", "y").agg(F.min("shingle").alias("shingle"), F.count(F.lit(1)).alias("w")).select("shingle", "p", "w")
    return entries.join(written(kept, "distinct-lists"), "shingle")


def _slot(doc_id: str) -> F.Column:
    """The place of an id in a bitmap; null ids share that of -1."""
    return F.coalesce(F.col(doc_id), F.lit(-1).cast("long")).alias(doc_id)


def _ids(col: pa.Array) -> np.ndarray:
    return col.fill_null(-1).to_numpy(zero_copy_only=False)


def _near(tail: str, percent: int) -> F.Column:
    """Set sizes and sketches that the similarity allows, for an entry and another whose columns end with `tail`."""
    a, b = F.col("n"), F.col(f"n{tail}")
    apart = sum((F.bit_count(F.col(p).bitwiseXOR(F.col(f"{p}{tail}"))) for p in SKETCH[1:]), F.bit_count(F.col(SKETCH[0]).bitwiseXOR(F.col(f"{SKETCH[0]}{tail}"))))
    return (100 * F.least(a, b) >= percent * F.greatest(a, b)) & (apart * (100 + percent) <= (100 - percent) * (a + b))


def _linked(listed: DataFrame, sets: DataFrame, percent: int) -> DataFrame:
    """node and root of all nodes with a link, from the lists (shingle, node, m, w, n, score, sketch).

    In a round each list is linked through two members: one of its largest component (first the member that shares most
    with others, so most likely the text that near copies stem from; then any, by a hash of list and node) and one from
    outside of it. A round costs two rows an entry at most. Rounds end when the pairs that are left cost no more than
    that, or when a round no longer takes enough of them away; then all the pairs left are formed.
    """
    marks = ("node", "n", "comp", *SKETCH)
    links: DataFrame | None = None
    tried: DataFrame | None = None
    roots = listed.sparkSession.createDataFrame([], "node long, root long")
    rest, last, k = listed, None, 0

    def add(pairs: DataFrame) -> None:
        nonlocal links, tried, roots
        pairs = written(pairs if tried is None else pairs.join(tried, ["a", "b"], "left_anti"), "pairs")
        good = written(_verified(pairs, sets, percent), "verified")
        tried = pairs if tried is None else tried.unionByName(pairs)
        if not good.isEmpty():
            links = good if links is None else links.unionByName(good)
            roots = written(connected_components(links), "roots")

    def near(outer: DataFrame, inner: DataFrame, *more: str) -> DataFrame:
        """Pairs of an outer entry and an inner one of the same list, in different components, that may be similar."""
        return outer.join(inner.select("shingle", *[F.col(c).alias(f"{c}_") for c in (*marks, *more)]), "shingle").where((F.col("comp") != F.col("comp_")) & _near("_", percent))

    a, b = F.least("node", "node_").alias("a"), F.greatest("node", "node_").alias("b")
    while True:
        here = rest.join(roots, "node", "left").withColumn("comp", F.coalesce("root", "node")).drop("root")
        comps = here.groupBy("shingle", "comp").agg(F.count(F.lit(1)).alias("q")).groupBy("shingle")
        lists = comps.agg(F.sum("q").alias("p"), F.max(F.struct("q", "comp")).alias("x"), F.count(F.lit(1)).alias("comps")).where("comps > 1")
        lists = written(lists.select("shingle", F.col("x.comp").alias("largest"), (F.col("p") - F.col("x.q")).alias("outside"), "p"), "mixed-lists")
        cost, entries = lists.agg(F.coalesce(F.sum(F.col("outside") * F.col("p")), F.lit(0)), F.coalesce(F.sum("p"), F.lit(0))).first()
        if not cost:
            return roots
        placed = written(here.join(lists.select("shingle", "largest"), "shingle"), "placed")
        outer = placed.where("comp <> largest")
        if last is not None and (cost <= 2 * entries or cost > ROUND_GAIN * last):
            break
        draw = F.xxhash64(F.lit(k), "shingle", "node")
        one = F.max_by(F.struct(*marks), F.struct("score", draw)) if k == 0 else F.min_by(F.struct(*marks), draw)
        two = F.max_by(F.struct(*marks), F.struct("score", draw)) if k % 2 else F.min_by(F.struct(*marks), draw)
        hubs = (placed if k == 0 else placed.where("comp = largest")).groupBy("shingle").agg(one.alias("x")).unionByName(outer.groupBy("shingle").agg(two.alias("x")))
        met = near(placed if k == 0 else outer, written(hubs.select("shingle", "x.*"), "hubs"))
        add(met.select(a, b).distinct())
        rest, last, k = placed.drop("comp", "largest"), cost, k + 1

    met = near(placed, outer, "m", "w").where((F.col("comp") == F.col("largest")) | (F.col("node") < F.col("node_")))
    pairs = met.groupBy(a, b).agg(F.sum("w").alias("k"), F.max(F.least("m", "m_")).alias("need"))
    add(pairs.where("k >= need").select("a", "b"))
    return roots


def op1_jaccard_join(spark, sf_dir: str) -> DataFrame:
    return jaccard_components(spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text"))


OP1_SQL = r"""
with recursive w as (
  select doc_id, list_filter(string_split_regex(translate(coalesce(text, ''), 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[ \t\n\x0b\f\r]+'), lambda x: x <> '') as w from documents
), sets as (
  select doc_id, case when len(w) = 0 then [] when len(w) < 3 then [array_to_string(w, ' ')] else list_distinct(list_transform(range(1, len(w) - 1), lambda i: w[i] || ' ' || w[i + 1] || ' ' || w[i + 2])) end as s from w
), sized as (select doc_id, len(s)::bigint as n from sets),
items as (select doc_id, unnest(s) as t from sets),
frequency as (select t, count(*) as k from items group by t having count(*) > 1),
shared as (select a.doc_id as a, b.doc_id as b, count(*) as k from items a join frequency using (t) join items b on a.t = b.t and a.doc_id < b.doc_id group by a.doc_id, b.doc_id),
links as (select a, b from shared join sized x on x.doc_id = a join sized y on y.doc_id = b where 100 * k >= 90 * (x.n + y.n - k)),
edges as (select a, b from links union all select b, a from links),
reach(a, b) as (select doc_id, doc_id from documents union select r.a, e.b from reach r join edges e on e.a = r.b)
select doc_id, n as n_shingles, least_id as component_id from sized join (select a, min(b) as least_id from reach group by a) r on r.a = doc_id
"""
