"""Mixing to target weights with soft membership.

A classifier fitted on a labelled table gives each document a posterior over domains; projected-gradient least squares
then finds document rates, within bounds, whose expected token totals by domain match the targets.
"""

from __future__ import annotations

import math
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from .common import free_name, mapped, rows_of, texts_of, written

#: Labelled documents fitted on, chosen by a hash over the whole table, and the longest text among them.
MAX_LABELLED_ROWS, MAX_LABELLED_BYTES = 2_000, 64 << 10
BUCKETS, STEPS, RATE, DECAY = 2048, 200, 2.0, 1e-3
#: Gradient steps over all rows at most, and steps over the cells of the membership histogram before them.
ROUNDS, CELL_STEPS = 12, 5_000
#: Steps end when no rate wants to move: the tokens by which one more step would change the mix, as a share of all.
STILL = 1e-5
#: The histogram has at most FINEST cells along a domain's axis, and about MOST_CELLS in all; it is all that the driver sees.
FINEST, MOST_CELLS = 32, 20_000


def bag(raw: bytes, known: dict[bytes, int]) -> tuple[int, np.ndarray]:
    """(number of words, unit-length vector of damped hashed word counts)."""
    words = raw.split()
    codes = []
    for w in words:
        if (k := known.get(w)) is None:
            k = zlib.crc32(w.lower().strip(b".,;:!?")) % BUCKETS
            if len(known) < 200_000:
                known[w] = k
        codes.append(k)
    v = np.log1p(np.bincount(np.array(codes, dtype=np.int64), minlength=BUCKETS))
    return len(words), (v / max(1e-9, np.sqrt(v @ v))).astype(np.float32)


def fit_posterior(x: np.ndarray, y: np.ndarray, n_domains: int) -> tuple[np.ndarray, np.ndarray]:
    """Multinomial logistic regression by full gradient steps: (weights, intercepts). Without rows: uniform."""
    w, b = np.zeros((BUCKETS, n_domains)), np.zeros(n_domains)
    if not len(y):
        return w, b
    b = np.log((np.bincount(y, minlength=n_domains) + 1) / (len(y) + n_domains))
    aim = np.eye(n_domains)[y]
    for _ in range(STEPS):
        g = (aim - posterior(x, w, b)) / len(y)
        w += RATE * len(b) * (x.T @ g) - DECAY * w
        b += RATE * g.sum(0)
    return w, b


def posterior(x: np.ndarray, w: np.ndarray, b: np.ndarray) -> np.ndarray:
    z = x @ w + b
    z = np.exp(z - z.max(axis=1, keepdims=True))
    return z / z.sum(axis=1, keepdims=True)


def memberships(docs: DataFrame, labels: DataFrame, domains: list[str], id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Add n_tokens (words) and membership (posterior over `domains`, array<double>) to every row of `docs`.

    `labels` holds doc_id and domain. At most MAX_LABELLED_ROWS labelled ids, a bound and not a share of the data, go
    into the scan's filter, which sends back those documents' bags; so no text is shuffled. An empty text has the bag zero and
    thus the prior.
    """
    known = rows_of(labels, doc_id="doc_id", domain="domain").where(F.col("doc_id").isNotNull() & F.col("domain").isin(*domains)).dropDuplicates(["doc_id"])
    share = min(1.0, 1.1 * MAX_LABELLED_ROWS / max(1, known.count()))
    picked = {r.doc_id: domains.index(r.domain) for r in known.where(F.pmod(F.xxhash64("doc_id"), F.lit(1_000_000)) < int(share * 1_000_000) + 1).limit(MAX_LABELLED_ROWS).collect()}
    texts = rows_of(docs, doc_id=id_col, text=F.coalesce(F.col(f"`{text_col}`"), F.lit(""))).where(F.col("doc_id").isin(*picked) & (F.octet_length("text") <= MAX_LABELLED_BYTES)) if picked else None

    def fetch(batches):
        words: dict[bytes, int] = {}
        for b in batches:
            hits = [(picked[i], bag(raw, words)[1].astype("<f2").tobytes()) for i, raw in zip(b.column(0).to_pylist(), texts_of(b, "text"))]
            if hits:
                yield pa.RecordBatch.from_arrays([pa.array([h[0] for h in hits], type=pa.int32()), pa.array([h[1] for h in hits], type=pa.binary())], names=["y", "x"])

    rows = texts.mapInArrow(fetch, "y int, x binary").limit(2 * MAX_LABELLED_ROWS).collect() if picked else []
    x = np.frombuffer(b"".join(r.x for r in rows), dtype="<f2").reshape(-1, BUCKETS).astype(np.float32)
    w, b = fit_posterior(x, np.array([r.y for r in rows], dtype=np.int64), len(domains))

    def kernel():
        words: dict[bytes, int] = {}

        def one(batch):
            n, p = [], []
            for begin in range(0, batch.num_rows, 512):
                bags = [bag(t, words) for t in texts_of(batch.slice(begin, 512), text_col)]
                n += [k for k, _ in bags]
                p.append(posterior(np.stack([v for _, v in bags]), w, b))
            flat = np.concatenate(p)
            return [pa.array(n, type=pa.int64()), pa.ListArray.from_arrays(pa.array(np.arange(0, flat.size + 1, flat.shape[1], dtype=np.int32)), pa.array(flat.ravel()))]

        return one

    return mapped(docs, {"n_tokens": "long", "membership": "array<double>"}, kernel)


def _clipped(x, least: float, most: float):
    return np.minimum(most, np.maximum(least, x))


def cell_rates(tokens: np.ndarray, sums: np.ndarray, wanted: np.ndarray, size: float, least: float, most: float) -> np.ndarray:
    """Accelerated projected-gradient steps on the cells of a histogram; `sums` holds each cell's tokens by domain.

    The momentum starts anew whenever it points uphill. Steps end when they no longer move tokens.
    """
    mean = sums / np.maximum(tokens, 1e-300)[:, None]
    rate = ahead = _clipped(np.ones(len(tokens)), least, most)
    pace = 1.0
    for _ in range(CELL_STEPS):
        now = _clipped(ahead - size * (mean @ (ahead @ sums - wanted)), least, most)
        if tokens @ np.abs(now - ahead) <= 1e-3 * STILL * tokens.sum():
            return now
        if (tokens * (ahead - now)) @ (now - rate) > 0:
            pace = 1.0
        faster = (1 + math.sqrt(1 + 4 * pace * pace)) / 2
        ahead, rate, pace = now + (pace - 1) / faster * (now - rate), now, faster
    return rate


def fit_rates(table: DataFrame, targets: dict[str, float], total: float | None = None, least: float = 0.0, most: float = 4.0, rounds: int = ROUNDS) -> tuple[DataFrame, np.ndarray, np.ndarray]:
    """Add `rate` to a table with n_tokens and membership (in the order of `targets`); also return (wanted, reached) totals by domain.

    Minimises the squared gap between the expected domain totals (sum of rate x tokens x membership) and the targets by
    projected gradient from rate 1: a step moves each rate against the gradient, which is its tokens times membership .
    gap, and clips it to [least, most]. Steps are measured in tokens, so a rate moves by step x membership . gap; the step is
    one over the largest eigenvalue of the token-weighted second moments of the memberships of all rows.

    First steps run on a histogram of the memberships, which is bounded at any size: cells hold exact sums, so totals are
    those of all rows, each at its cell's rate. The remaining steps run over all rows, one aggregation a step, each
    row by its own membership, until no rate wants to move. Rates are nested column expressions: no row state is written,
    and a lost executor costs a task. Where targets can be met in several ways, rates stay near 1. Targets are normalised to
    sum to `total` (default: the tokens there are). Rows without tokens get a rate but add nothing.
    """
    d, p, t = len(targets), F.col("membership"), F.col("n_tokens")
    wanted = np.array(list(targets.values()), dtype=float)
    wanted = wanted / wanted.sum() if wanted.sum() else np.full(d, 1 / d)
    cuts = FINEST
    while cuts > 1 and math.comb(cuts + d - 1, d - 1) > MOST_CELLS:
        cuts -= 1
    at, first = [free_name(table.columns, f"at_{k}") for k in range(d)], free_name(table.columns, "first_rate")
    places = [F.round(p[k] * cuts).cast("int").alias(c) for k, c in enumerate(at)]
    pairs = [(i, j) for i in range(d) for j in range(i, d)]
    sums = [*[F.sum(t * p[k]) for k in range(d)], F.sum(t), *[F.sum(t * p[i] * p[j]) for i, j in pairs]]
    cells = table.where(t > 0).groupBy(*places).agg(*[x.alias(f"sum_{k}") for k, x in enumerate(sums)]).toPandas().sort_values(at)
    got = cells[[f"sum_{k}" for k in range(len(sums))]].to_numpy(dtype=float).reshape(len(cells), len(sums))
    tokens, by_domain = got[:, d], got[:, :d]
    wanted = wanted * float(tokens.sum() * (1 if total is None else total))
    moments = np.zeros((d, d))
    for (i, j), v in zip(pairs, got[:, d + 1 :].sum(axis=0)):
        moments[i, j] = moments[j, i] = v
    size = 1 / max(1e-9, np.linalg.eigvalsh(moments)[-1]) if len(cells) else 0.0
    start = cell_rates(tokens, by_domain, wanted, size, least, most) if len(cells) else np.zeros(0)

    known = table.sparkSession.createDataFrame([(*map(int, c), float(r)) for c, r in zip(cells[at].to_numpy(), start)], ", ".join([*[f"{c} int" for c in at], f"{first} double"]))
    placed = table.select("*", *places).join(F.broadcast(known), at, "left")  # a row for each cell: at most about MOST_CELLS
    one = F.lit(float(_clipped(1.0, least, most)))
    rate = F.coalesce(F.col(first), one)
    reached = start @ by_domain if len(cells) else np.zeros(d)

    def stepped(now: Column, gap: np.ndarray) -> Column:
        moved = now - sum((F.lit(float(size * g)) * p[k] for k, g in enumerate(gap)), F.lit(0.0))
        return F.least(F.lit(float(most)), F.greatest(F.lit(float(least)), moved))

    for _ in range(rounds if len(cells) else 0):
        after = stepped(rate, reached - wanted)
        rows = placed.where(t > 0).select(t, p, rate.alias("was"), after.alias("now"))
        got = rows.agg(F.sum(t * F.abs(F.col("now") - F.col("was"))), *[F.sum(F.col("now") * t * p[k]) for k in range(d)]).first()
        rate, reached = after, np.array(got[1:], dtype=float)
        if got[0] <= STILL * tokens.sum():
            break
    return placed.withColumn("rate", rate).drop(*at, first), wanted, reached


def mix_to_targets(docs: DataFrame, labels: DataFrame, targets: dict[str, float], total: float | None = None, least: float = 0.0, most: float = 4.0, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Every row of `docs` with n_tokens, membership, rate and copies; input columns of these names are replaced.

    `total` is the aimed token total as a multiple of the present one. copies is the rate rounded up or down at
    random by a hash of the id, so that its expectation is the rate; rows that share an id, or a null id, share the
    draw. Null and empty texts have no tokens and the prior as membership. Domains without labelled rows get
    posteriors near zero; their targets are then met as far as the bounds allow.
    """
    domains = list(targets)
    table = written(memberships(docs, labels, domains, id_col, text_col), "memberships")
    rated, _, _ = fit_rates(table, targets, total, least, most)
    draw = F.pmod(F.xxhash64(F.lit("copies"), F.col(f"`{id_col}`")), F.lit(1_000_000)) / 1_000_000
    whole = F.floor("rate")
    return rated.withColumn("copies", (whole + F.when(draw < F.col("rate") - whole, 1).otherwise(0)).cast("int"))


#: Domains of the labels table and the share of tokens each is to have.
TARGETS = {"good": 0.87, "good_toxic": 0.06, "poor": 0.06, "poor_toxic": 0.01}


def label_domains(labels: DataFrame) -> DataFrame:
    """doc_id and domain of the labels table (rows with a null label have none)."""
    kind = F.concat(F.when(F.col("quality") == 1, "good").when(F.col("quality") == 0, "poor"), F.when(F.col("toxic") == 1, "_toxic").when(F.col("toxic") == 0, ""))
    return labels.select("doc_id", kind.alias("domain"))


def op6_mixing(spark, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    labels = label_domains(spark.read.parquet(f"{sf_dir}/labels.parquet"))
    return mix_to_targets(docs, labels, TARGETS).select("doc_id", "n_tokens", *[F.round(F.col("membership")[k], 9).alias(f"p_{d}") for k, d in enumerate(TARGETS)], F.round("rate", 9).alias("rate"), "copies")
