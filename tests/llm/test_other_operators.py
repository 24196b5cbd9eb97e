import base64
import gzip
import hashlib
import math
from collections import Counter, defaultdict

import numpy as np
import pytest

import corpus_pipeline
from sizeprofile.llm import mixing, quality_gam, topk, warc
from sizeprofile.llm.common import work_path
from sizeprofile.llm.components import connected_components

from .cases import documents, rows

PAGES = [(1, "http://a/é x\r\n", "<p>one</p>"), (2, None, "<p>one</p>"), (3, "u", None), (4, "u", ""), (5, "u", "x" * 300_000), (None, "u", "<p>one</p>"), (2, "v", "<p>one</p>"), (6, "w", "日本語\r\n\r\nWARC/1.1"), (7, "w", "only"), (7, "w", "only"), (None, "n", "nobody")]


def pages(spark, some=PAGES):
    return spark.createDataFrame([(*p, 1, "x") for p in some], "page_id long, url string, html string, payload int, first string")


@pytest.mark.parametrize("split_bytes, file_bytes, least", [(1 << 20, 1 << 20, 0), (97, 300, 0), (97, 300, 8)])
def test_warc_round_trip(spark, split_bytes, file_bytes, least):
    files = warc.write_warc(pages(spark), work_path(spark, "w"), least, file_bytes=file_bytes)
    got = warc.read_warc(files, split_bytes).collect()
    first = {}
    for i, _, html in PAGES:
        raw = (html or "").encode()
        if i is not None and len(raw) >= least:
            first[raw] = min(i, first.get(raw, i))
    want = Counter()
    for i, _, html in PAGES:
        raw = (html or "").encode()
        of = first.get(raw)
        of = None if of == i else of
        want[i, len(raw), base64.b32encode(hashlib.sha1(raw).digest()).decode(), "response" if of is None else "revisit", of, raw if of is None else None] += 1
    assert Counter((r.page_id, r.payload_bytes, r.payload_digest, r.record_type, r.refers_to, None if r.payload is None else bytes(r.payload)) for r in got) == want


def test_warc_reads_as_many_records_as_written_with_very_long_urls(spark):
    long = "http://a/" + "é" * 300_000  # 1.8 MB when percent-encoded
    files = warc.write_warc(pages(spark, [(1, "u", "before"), (2, long, "long"), (3, "v", "after")]).coalesce(1), work_path(spark, "w"))
    got = warc.read_warc(files).collect()
    assert len(got) == sum(r.n_records for r in files.collect()) == 3
    assert {(r.page_id, bytes(r.payload)) for r in got} == {(1, b"before"), (2, b"long"), (3, b"after")}


def test_warc_reader_passes_over_chance_magic(spark, tmp_path):
    inner = gzip.compress(b"not a record")
    raw = b"".join(gzip.compress(warc.record(k, "u", f"page {k}".encode(), None)) for k in range(40))
    path = tmp_path / "x.warc.gz"
    path.write_bytes(raw)
    assert b"\x1f\x8b\x08" in inner
    for step in (1 << 20, 64, 17):
        seen = [f["warc-record-id"] for at in range(0, len(raw), step) for f, _, _ in warc.records_in(str(path), at, at + step)]
        assert seen == [f"<urn:page:{k}>" for k in range(40)]


@pytest.mark.parametrize("split_bytes", [1 << 20, 700])
def test_warc_reader_raises_when_a_record_is_lost(spark, tmp_path, split_bytes):
    members = [gzip.compress(warc.record(k, "u", f"page {k} {'x' * k}".encode(), None)) for k in range(30)]
    raw = b"".join(members)
    at = len(b"".join(members[:11]))
    path = tmp_path / "x.warc.gz"
    listed = spark.createDataFrame([(str(path), 30, len(raw))], "path string, n_records long, n_bytes long")
    read = lambda **kw: [r.page_id for r in warc.read_warc(listed, split_bytes, **kw).collect()]
    path.write_bytes(raw)
    assert sorted(read()) == list(range(30))
    spoilt = {"end": raw[:-5] + b"spoil", "body": raw[: at + 60] + b"?" + raw[at + 61 :], "magic": raw[:at] + b"?" + raw[at + 1 :], "first": b"?" + raw[1:], "cut": raw[:-9], "gone": raw[:at] + raw[at + len(members[11]) :], "last gone": raw[: -len(members[29])]}
    for kind, now in spoilt.items():
        path.write_bytes(now)
        with pytest.raises(Exception, match="no whole record|are listed"):
            read()
        left = read(skip_damaged=True)
        assert len(left) == len(set(left)) and 26 <= len(left) < 30, kind


def test_warc_of_an_empty_table(spark):
    assert warc.read_warc(warc.write_warc(pages(spark, []), work_path(spark, "w"))).count() == 0


VECTORS = [(k, [math.sin(k * j + 1) for j in range(9)]) for k in range(60)] + [(200, None), (201, [1.0, None]), (202, [float("nan")] * 9), (203, [float("inf")] * 9), (None, [1.0] * 9), (7, [0.5] * 9), (7, [0.5] * 9), (300, [2.0, -1.0]), (301, []), (400, [0.25] * 9), (401, [0.25] * 9), (402, [0.25] * 9), (450, [1e13] * 9), (500, [-1e13] * 9)]


@pytest.mark.parametrize("limit, tile, cell", [(8 << 20, 4096, 1 << 20), (0, 7, 1 << 20), (0, 7, 500)])
def test_top_k_against_brute_force(spark, monkeypatch, limit, tile, cell):
    monkeypatch.setattr(topk, "BROADCAST_BYTES", limit)
    monkeypatch.setattr(topk, "CELL_BYTES", cell)
    monkeypatch.setattr(topk, "TILE_ROWS", tile)
    monkeypatch.setattr(topk, "TILE_QUERIES", 3)
    v = spark.createDataFrame([(i, e, 5, 0) for i, e in VECTORS], "vec_id long, embedding array<double>, tile int, floor int")
    got = topk.top_k(v, v.where("vec_id % 50 = 0 or vec_id = 7"), k=5)
    whole = [(i, [math.floor(256 * x) for x in e]) for i, e in VECTORS if i is not None and e is not None and all(x is not None and math.isfinite(x) for x in e)]
    want = Counter()
    asked = {(i, tuple(e)) for i, e in whole if i % 50 == 0 or i == 7}
    for qi, q in asked:
        scored = sorted((-max(-(2**63), min(2**63 - 1, sum(a * b for a, b in zip(q, c)))), i) for i, c in whole if i != qi)[:5]
        for rank, (s, i) in enumerate(scored, 1):
            want[qi, rank, i, -s] += 1
    assert Counter(map(tuple, got.collect())) == want


def test_top_k_without_queries(spark):
    v = spark.createDataFrame(VECTORS, "vec_id long, embedding array<double>")
    assert topk.top_k(v, v.where("false")).count() == 0
    assert topk.top_k(v.where("vec_id = 3"), v.where("vec_id = 3")).count() == 0


def test_components(spark):
    import random

    rnd = random.Random(1)
    edges = [(rnd.randrange(400), rnd.randrange(400)) for _ in range(300)] + [(k, k + 1) for k in range(500, 540)] + [(5, 5)]
    parent = list(range(600))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in edges:
        parent[max(find(a), find(b))] = min(find(a), find(b))
    nodes = {x for e in edges if e[0] != e[1] for x in e}
    got = connected_components(spark.createDataFrame(edges, "a long, b long"))
    assert Counter(map(tuple, got.collect())) == Counter((x, find(x)) for x in nodes)
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_gam_on_held_out_rows(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = spark.read.parquet("/root/testdata/sf0.01/labels.parquet")
    got = quality_gam.score_quality(docs, labels).join(labels, "doc_id").where("held_out").collect()
    assert sum(r.predicted == r.quality for r in got) / len(got) > 0.93
    assert all(0 <= r.score <= 1 for r in got)


def test_gam_edge_cases(spark):
    docs = documents(spark)
    labels = spark.createDataFrame([(k, k % 2, 0) for k in range(60)] + [(None, 1, 0), (3, None, 0)], "doc_id long, quality int, y int")
    assert Counter(r.doc_id for r in quality_gam.score_quality(docs, labels).collect()) == Counter(r[0] for r in rows())
    nothing = labels.where("false")
    assert {r.score for r in quality_gam.score_quality(docs, nothing).collect()} == {0.5}
    assert quality_gam.score_quality(documents(spark, []), nothing).count() == 0


def test_gam_learns_an_interaction():
    rnd = np.random.default_rng(0)
    x = rnd.normal(size=(4000, 3))
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0)).astype(float)
    s = quality_gam.fit_gam(x, y).scores(x)
    assert ((s > 0.5) == y).mean() > 0.9


def test_mixing_meets_targets(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    labels = mixing.label_domains(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"))
    table = mixing.memberships(docs.select("doc_id", "text"), labels, list(mixing.TARGETS)).cache()
    wanted = {"good": 0.85, "good_toxic": 0.07, "poor": 0.07, "poor_toxic": 0.01}
    rated, want, reached = mixing.fit_rates(table, wanted)
    assert np.allclose(want, reached, atol=0.01 * want.sum())
    r = rated.toPandas()
    again = [(r.rate * r.n_tokens * r.membership.map(lambda m: m[k])).sum() for k in range(4)]
    assert np.allclose(again, reached)
    assert r.rate.between(0, 4).all() and np.allclose(r.membership.map(sum), 1)
    # the least-squares optimum: no feasible direction lowers the gap
    few = table.limit(40)
    _, want, reached = mixing.fit_rates(few.cache(), {"good": 0.5, "good_toxic": 0.2, "poor": 0.2, "poor_toxic": 0.1}, most=1.5)
    p = few.toPandas()
    a = np.stack([p.n_tokens * p.membership.map(lambda m: m[k]) for k in range(4)])
    rate = np.ones(len(p))
    step = 1 / np.linalg.norm(a, 2) ** 2
    for _ in range(100_000):
        rate = np.clip(rate + step * (a.T @ (want - a @ rate)), 0, 1.5)
    assert np.linalg.norm(want - reached) <= 1.05 * np.linalg.norm(want - a @ rate) + 1e-3 * want.sum()


def test_mixing_when_all_rates_start_on_a_bound(spark):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet").select("doc_id", "text")
    labels = mixing.label_domains(spark.read.parquet("/root/testdata/sf0.01/labels.parquet"))
    table = mixing.memberships(docs, labels, list(corpus_pipeline.MIX)).cache()
    most = corpus_pipeline.MIX_MOST
    rated, want, reached = mixing.fit_rates(table, corpus_pipeline.MIX, corpus_pipeline.MIX_TOTAL, least=1.0, most=most)
    p = rated.select("n_tokens", "membership", "rate").toPandas()
    a = np.stack([p.n_tokens * p.membership.map(lambda m: m[k]) for k in range(4)])
    rate, step = np.ones(len(p)), 1 / np.linalg.norm(a, 2) ** 2
    for _ in range(20_000):
        rate = np.clip(rate + step * (a.T @ (want - a @ rate)), 1.0, most)
    assert np.linalg.norm(want - reached) <= 1.01 * np.linalg.norm(want - a @ rate) + 1e-3 * want.sum()
    assert p.rate.between(1.0, most).all() and p.rate.max() >= 2  # rows of rate 2 have two copies or more


def plain_boosting(x, y, bins, pair_bins, n_pairs, rounds, pair_rounds, rate, leaves):
    """The additive model row by row, with every cut of a tree tried over its rows: the scores of the rows."""
    rows, n_features = range(len(y)), len(x[0])
    cuts = [sorted(set(np.quantile([r[f] for r in x], np.linspace(0, 1, bins + 1)[1:-1]).tolist())) for f in range(n_features)]
    code = [[sum(c <= r[f] for c in cuts[f]) for r in x] for f in range(n_features)]
    coarse = [[c * pair_bins // (len(cuts[f]) + 1) for c in code[f]] for f in range(n_features)]
    base = (sum(y) + 1) / (len(y) + 2)
    total = [math.log(base / (1 - base))] * len(y)

    def slopes():
        p = [1 / (1 + math.exp(-t)) for t in total]
        return [a - b for a, b in zip(y, p)], [b * (1 - b) for b in p]

    def sums(v, some):
        return sum(v[i] for i in some)

    gain = lambda g, h, some: sums(g, some) ** 2 / (sums(h, some) + 1)
    newton = lambda g, h, some: sums(g, some) / (sums(h, some) + 1)
    for _ in range(rounds):
        for f in range(n_features):
            g, h = slopes()
            leaf = [list(rows)]
            spans = [(0, len(cuts[f]) + 1)]
            while len(leaf) < leaves:
                options = []
                for k, (some, (lo, hi)) in enumerate(zip(leaf, spans)):
                    for cut in range(lo + 1, hi):
                        low, high = [i for i in some if code[f][i] < cut], [i for i in some if code[f][i] >= cut]
                        options.append((gain(g, h, low) + gain(g, h, high) - gain(g, h, some), -cut, k, low, high))
                if not options or max(options)[0] <= 1e-9:
                    break
                _, cut, k, low, high = max(options)
                lo, hi = spans[k]
                leaf[k : k + 1], spans[k : k + 1] = [low, high], [(lo, -cut), (-cut, hi)]
            for some in leaf:
                step = rate * newton(g, h, some)
                for i in some:
                    total[i] += step

    def quadrants(f, k):
        g, h = slopes()
        best = None
        for a in range(1, pair_bins):
            for b in range(1, pair_bins):
                parts = [[i for i in rows if (coarse[f][i] < a) == s and (coarse[k][i] < b) == t] for s in (True, False) for t in (True, False)]
                got = sum(gain(g, h, p) for p in parts)
                if best is None or got > best[0] + 1e-12:
                    best = (got, parts)
        return best[0], [(p, newton(g, h, p)) for p in best[1]]

    ranked = sorted(((quadrants(f, k)[0], f, k) for f in range(n_features) for k in range(f + 1, n_features)), reverse=True)[:n_pairs]
    for _ in range(pair_rounds):
        for _, f, k in ranked:
            for some, step in quadrants(f, k)[1]:
                for i in some:
                    total[i] += rate * step
    return [1 / (1 + math.exp(-t)) for t in total]


def test_gam_against_plain_boosting(monkeypatch):
    small = {"BINS": 6, "PAIR_BINS": 3, "PAIRS": 2, "ROUNDS": 6, "PAIR_ROUNDS": 4, "RATE": 0.3, "LEAVES": 3}
    for name, value in small.items():
        monkeypatch.setattr(quality_gam, name, value)
    rnd = np.random.default_rng(2)
    x = np.c_[rnd.normal(size=(150, 3)), rnd.integers(0, 3, 150)]
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.3) | (rnd.random(150) < 0.1)).astype(float)
    want = plain_boosting(x.tolist(), y.tolist(), 6, 3, 2, 6, 4, 0.3, 3)
    assert np.allclose(quality_gam.fit_gam(x, y).scores(x), want, atol=1e-9)


@pytest.mark.parametrize("least, most, total", [(0.0, 4.0, 1.0), (0.0, 0.8, 1.0), (1.2, 3.0, 1.5), (1.0, 1.0, 2.0), (0.25, 3.0, 1.1)])
@pytest.mark.parametrize("shares", [(0.25, 0.25, 0.25, 0.25), (0.87, 0.06, 0.06, 0.01), (0.0, 0.0, 1.0, 0.0)])
def test_rates_reach_the_residual_of_a_plain_solver(spark, least, most, total, shares):
    rnd = np.random.default_rng(5)
    p = rnd.dirichlet([2.0, 0.3, 0.5, 0.1], 300)
    t = np.r_[np.exp(rnd.normal(5, 1.5, 298)).astype(int), 0, 40_000]
    table = spark.createDataFrame([(int(n), m.tolist(), 0, 1.0) for n, m in zip(t, p)], "n_tokens long, membership array<double>, at_0 int, first_rate double")
    rated, want, reached = mixing.fit_rates(table, dict(zip("abcd", shares)), total, least, most)
    a = t * p.T
    rate, size = np.clip(np.ones(300), least, most), 1 / np.linalg.eigvalsh((t * p.T) @ p)[-1]
    for _ in range(40_000):
        rate = np.clip(rate - size * (p @ (a @ rate - want)), least, most)
    assert np.linalg.norm(want - reached) <= 1.01 * np.linalg.norm(want - a @ rate) + 1e-3 * want.sum()
    got = rated.select("rate", "n_tokens", "membership", "at_0", "first_rate").collect()
    assert np.allclose(sum(r.rate * r.n_tokens * np.array(r.membership) for r in got), reached)
    assert all(least - 1e-12 <= r.rate <= most + 1e-12 for r in got) and {(r.at_0, r.first_rate) for r in got} == {(0, 1.0)}


def test_pipeline_mixing_brings_the_mix_to_its_targets(spark):
    sf = "/root/testdata/sf0.01"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = mixing.label_domains(spark.read.parquet(f"{sf}/labels.parquet"))
    table = mixing.memberships(docs.select("doc_id", "text"), labels, list(corpus_pipeline.MIX)).cache()
    m = {r.doc_id: r.n_tokens * np.array(r.membership) for r in table.collect()}
    mixed = Counter(r.doc_id for r in corpus_pipeline.mixing_stage(spark, docs, sf).collect())
    before, after = sum(m.values()), sum(n * m[i] for i, n in mixed.items())
    want = np.array(list(corpus_pipeline.MIX.values())) * corpus_pipeline.MIX_TOTAL * before.sum()
    assert np.linalg.norm(after - want) < 0.6 * np.linalg.norm(before - want)
    assert len(mixed) == docs.count() < sum(mixed.values()) and max(mixed.values()) >= 2  # none is dropped, some are repeated
    rated, _, _ = mixing.fit_rates(table, corpus_pipeline.MIX, corpus_pipeline.MIX_TOTAL, corpus_pipeline.MIX_LEAST, corpus_pipeline.MIX_MOST)
    rate = [r.rate for r in rated.collect()]
    assert min(rate) == 1 and max(rate) > 1.5 and sum(x > 1.01 for x in rate) > 0.05 * len(rate)


def test_mixing_edge_cases(spark):
    labels = spark.createDataFrame([(k, "a" if k % 2 else "b") for k in range(60)] + [(None, "a"), (1, None), (2, "c")], "doc_id long, domain string")
    out = mixing.mix_to_targets(documents(spark), labels, {"a": 1.0, "b": 1.0}).collect()
    assert Counter(r.doc_id for r in out) == Counter(r[0] for r in rows())
    by_id = defaultdict(set)
    for r in out:
        by_id[r.doc_id, r.text].add(r.copies)
    assert all(len(v) == 1 for v in by_id.values())
    assert mixing.mix_to_targets(documents(spark, []), labels, {"a": 1.0, "b": 1.0}).count() == 0
    none = mixing.mix_to_targets(documents(spark), labels.where("false"), {"a": 3.0, "b": 1.0}).collect()
    assert all(np.allclose(r.membership, 0.5) for r in none)


def test_pipeline_stages(spark):
    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{sf}/labels.parquet").collect()}
    columns, n = docs.columns, docs.count()
    ids = {r.doc_id for r in docs.select("doc_id").collect()}
    short = {r.doc_id for r in docs.collect() if len(r.text.split()) < 50}
    for name, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, sf).cache()
        assert docs.columns == columns, name
        left = {r.doc_id for r in docs.select("doc_id").collect()}
        assert left and left <= ids
        if name == "quality_rules":
            clean = {i for i in ids if labels.get(i) == 1 and i not in short}
            assert len(clean & left) > 0.97 * len(clean)
        if name == "mixing":
            assert left == ids and docs.count() > len(ids)
        ids = left
    out = corpus_pipeline.STAGES[-1][1](spark, docs, sf)
    assert out.count() == docs.count() and out.where("n_tokens = 0").count() == docs.where("text = ''").count()
    assert n > len(ids)


@pytest.mark.parametrize("k", range(len(corpus_pipeline.STAGES)))
def test_pipeline_stages_on_edge_cases(spark, k):
    name, stage = corpus_pipeline.STAGES[k]
    for some in (None, []):
        docs = documents(spark, some)
        out = stage(spark, docs, "/root/testdata/sf0.001")
        if name == "bpe":
            assert out.count() == docs.count()
        else:
            assert out.columns == docs.columns
            assert (out.count() == 0) == (some == [])


def test_pipeline_keeps_one_of_each_group(spark):
    docs = documents(spark)
    left = Counter(r.doc_id for r in corpus_pipeline.near_duplicates_stage(spark, docs, "").collect())
    assert left[1] == 1 and not {2, 3} & set(left)
    assert left[4] == left[5] == left[6] == left[8] == 1 and 9 not in left and left[None] == 1
