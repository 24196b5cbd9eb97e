import re
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
import tiktoken
from tokenizers import Tokenizer

from sizeprofile.llm import bpe, jaccard_join, line_dedup, quality_rules, substring_dedup, token_files
from sizeprofile.llm.common import work_path

from .cases import documents, rows

SPACE = " \t\n\x0b\x0c\r"
MULTI = "byte_bpe_multi_50k.tiktoken"


def lower(text):
    return re.sub("[A-Z]", lambda m: m[0].lower(), text)


def test_line_dedup_against_brute_force(spark):
    out = line_dedup.dedup_lines(documents(spark), threshold=10)
    key = lambda line: lower(line.strip(SPACE))
    where = defaultdict(set)
    for i, t, *_ in rows():
        for line in (t or "").split("\n"):
            where[key(line)].add(i)
    gone = {k for k, v in where.items() if k and len(v) >= 10}
    assert gone
    want = Counter((i, "\n".join(x for x in (t or "").split("\n") if key(x) not in gone), (t or "").count("\n") + 1) for i, t, *_ in rows())
    assert Counter((r.doc_id, r.text, r.n_lines) for r in out.collect()) == want
    assert set(out.columns) == {*documents(spark).columns, "n_lines"}
    assert dict(out.dtypes)["n_dropped"] == "bigint"


def test_line_dedup_of_rows_that_share_an_id(spark):
    frequent = [(k, f"often\nown {k}") for k in range(10)]
    shared = [(None, "often\nfirst"), (None, "second\noften"), (None, "third\nfourth"), (None, None), (3, "clean\noften\nOFTEN "), (3, "also\nclean")]
    out = line_dedup.dedup_lines(spark.createDataFrame(frequent + shared, "doc_id long, text string"))
    want = [(k, f"own {k}", 2, 1) for k in range(10)] + [(None, "first", 2, 1), (None, "second", 2, 1), (None, "third\nfourth", 2, 0), (None, "", 1, 0), (3, "clean", 3, 2), (3, "also\nclean", 2, 0)]
    assert Counter(map(tuple, out.select("doc_id", "text", "n_lines", "n_dropped").collect())) == Counter(want)


def test_line_dedup_plan_is_native(spark):
    plan = line_dedup.dedup_lines(documents(spark))._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas|Cartesian|NestedLoop", plan)


SKEW = {"spark.sql.adaptive.enabled": "true", "spark.sql.autoBroadcastJoinThreshold": "-1", "spark.sql.adaptive.autoBroadcastJoinThreshold": "-1", "spark.sql.shuffle.partitions": "16", "spark.sql.adaptive.coalescePartitions.enabled": "false", "spark.sql.adaptive.advisoryPartitionSizeInBytes": "2k", "spark.sql.adaptive.skewJoin.skewedPartitionThresholdInBytes": "2k", "spark.sql.adaptive.skewJoin.skewedPartitionFactor": "1.2"}


def skew_splits(spark, make) -> int:
    """Joins of the frame that `make` returns that AQE splits, with tiny thresholds and no broadcasts."""
    kept = {k: spark.conf.get(k, None) for k in SKEW}
    try:
        for k, v in SKEW.items():
            spark.conf.set(k, v)
        out = make()
        out.collect()
        return out._jdf.queryExecution().executedPlan().toString().count("skew=true")
    finally:
        for k, v in kept.items():
            spark.conf.unset(k) if v is None else spark.conf.set(k, v)


def test_hot_keys_are_split(spark):
    import random

    from sizeprofile.llm import warc

    rnd = random.Random(3)
    lines = [(k, "\n".join(["the very common line", *(" ".join(str(rnd.random()) for _ in range(3)) for _ in range(3))] + [f"often {k % 40}"])) for k in range(3000)]
    docs = spark.createDataFrame(lines, "doc_id long, text string").repartition(12).cache()
    assert skew_splits(spark, lambda: line_dedup.dedup_lines(docs)) >= 1
    pages = spark.createDataFrame([(k, "u", "hot" * 300 if k % 3 == 0 else f"p{k // 2} " * 90) for k in range(3000)], "page_id long, url string, html string").repartition(12).cache()
    assert skew_splits(spark, lambda: warc.with_first_copies(pages)) >= 1


@pytest.mark.parametrize("make", [
    lambda d: line_dedup.dedup_lines(d), lambda d: quality_rules.quality_rules(d), lambda d: jaccard_join.jaccard_components(d),
    lambda d: substring_dedup.remove_repeated(d), lambda d: bpe.bpe_encode(d, public_tokenizers.path(MULTI), public_tokenizers.PATTERN),
])
def test_empty_table(spark, make):
    assert make(documents(spark, [])).count() == 0


def brute_components(docs, percent, width):
    sets = []
    for i, t in docs:
        w = re.findall(f"[^{SPACE}]+", lower(t or ""))
        sets.append(frozenset(tuple(w[k : k + width]) for k in range(len(w) - width + 1)) if len(w) >= width else frozenset([tuple(w)] if w else []))
    parent = list(range(len(docs)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a in range(len(docs)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                parent[find(a)] = find(b)
    ids = defaultdict(list)
    for k, (i, _) in enumerate(docs):
        ids[find(k)].append(i)
    return Counter((i, len(sets[k]), min((x for x in ids[find(k)] if x is not None), default=None) if sets[k] else i) for k, (i, _) in enumerate(docs))


@pytest.mark.parametrize("percent, width", [(90, 3), (80, 5), (50, 1)])
def test_jaccard_join_against_brute_force(spark, percent, width):
    got = jaccard_join.jaccard_components(documents(spark), percent, width)
    assert Counter(map(tuple, got.collect())) == brute_components([r[:2] for r in rows()], percent, width)


def test_jaccard_join_on_chains_and_frequent_shingles(spark):
    import random

    rnd, docs = random.Random(7), []
    for family in range(6):
        text = [f"w{family}x{k}" for k in range(60)]
        for k in range(40):  # neighbours in the chain are similar, its ends are not
            text = [*text]
            text[rnd.randrange(60)] = f"e{family}y{k}"
            docs.append((len(docs), " ".join([*("common words shared by all of these texts ".split() * 2), *text])))
    got = jaccard_join.jaccard_components(spark.createDataFrame(docs, "doc_id long, text string"), 80, 1)
    assert Counter(map(tuple, got.collect())) == brute_components(docs, 80, 1)


def test_substring_dedup_against_brute_force(spark):
    for length in (70, 200):
        got = substring_dedup.remove_repeated(documents(spark), length)
        raw = [(i, (t or "").encode()) for i, t, *_ in rows()]
        seen = Counter(b[k : k + length] for _, b in raw for k in range(len(b) - length + 1))
        want = Counter()
        for i, b in raw:
            cut = np.zeros(len(b), dtype=bool)
            for k in range(len(b) - length + 1):
                if seen[b[k : k + length]] > 1:
                    cut[k : k + length] = True
            spans = int((np.diff(np.r_[0, cut.astype(int)]) == 1).sum())
            want[i, len(b), int(cut.sum()), spans, bytes(np.frombuffer(b, dtype=np.uint8)[~cut])] += 1
        assert Counter((r.doc_id, r.n_bytes, r.n_removed, r.n_spans, bytes(r.kept)) for r in got.collect()) == want
        assert "rest" in got.columns and "h1" in got.columns


def test_substring_dedup_joins_no_context_that_very_many_texts_hold(spark):
    passage = " ".join(f"passage{k}" for k in range(60))
    docs = [(k, f"{passage}{chr(48 + k)}own") for k in range(60)] + [(100, "a text of its own"), (101, passage[:-1]), (102, None)]
    got = substring_dedup.remove_repeated(spark.createDataFrame(docs, "doc_id long, text string"))
    plan = got._jdf.queryExecution().executedPlan().toString()
    assert "LeftSemi" not in plan and "LeftAnti" not in plan
    left = {r.doc_id: bytes(r.kept) for r in got.collect()}
    assert all(left[k] == f"{chr(48 + k)}own".encode() for k in range(60))
    assert left[100] == b"a text of its own" and left[101] == b"" and left[102] == b""


def test_interval_expansion_against_brute_force():
    import random

    rnd = random.Random(3)
    for _ in range(150):
        n = rnd.choice([2, 4, 7])
        parts = [bytes(rnd.choice(b"ab\0") for _ in range(rnd.randint(n, 40))) for _ in range(rnd.randint(1, 6))]
        text, valid, at = b"\0".join(parts), [], 0
        for p in parts:
            valid += range(at, at + len(p) - n + 1)
            at += len(p) + 1
        seen = Counter(text[v : v + n] for v in valid)
        assert substring_dedup.repeated_starts(text, np.array(valid), n).tolist() == [v for v in valid if seen[text[v : v + n]] > 1]


def test_bpe_equals_the_library_and_round_trips(spark):
    path = public_tokenizers.path(MULTI)
    out = bpe.bpe_decode(bpe.bpe_encode(documents(spark), path, public_tokenizers.PATTERN), path)
    ranks = {t: i for i, t in enumerate(bpe.load_ranks(path)) if t}
    library = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for r in out.collect():
        assert np.frombuffer(r.ids, dtype="<u4").tolist() == library.encode_ordinary(r.text or "")
        assert r.decoded == (r.text or "").encode()


def test_merge_replay_with_lower_ranks_later():
    """A vocabulary whose merges form lower ranks, against the plain one-word method."""
    import random

    rnd = random.Random(5)
    tokens = [bytes([b]) for b in range(256)] + [b"cd", b"abcd", b"aaa", b"ab", b"aa", b"bcd", b"abab", b"aaaa", b"ba"]
    rank = {t: i for i, t in enumerate(tokens)}

    def plain(word):
        if word in rank:
            return [rank[word]]
        parts = [word[k : k + 1] for k in range(len(word))]
        while True:
            best = min(((rank[a + b], k) for k, (a, b) in enumerate(zip(parts, parts[1:])) if a + b in rank), default=None)
            if best is None:
                return [rank[p] for p in parts]
            k = best[1]
            parts[k : k + 2] = [parts[k] + parts[k + 1]]

    all_words = list({bytes(rnd.choice(b"abcd") for _ in range(rnd.randint(0, 14))) for _ in range(3000)})
    got = bpe.MergeReplay(tokens).encode(all_words)
    assert [np.frombuffer(g, dtype="<u4").tolist() for g in got] == [plain(w) for w in all_words]


def test_token_files_round_trip(spark):
    path = public_tokenizers.path("byte_bpe_50k.json")
    files, dictionary = token_files.write_token_files(documents(spark), work_path(spark, "t"), path, end_id=2, file_bytes=20_000)
    assert files.count() > 3
    got = token_files.read_token_files(files, dictionary).collect()
    library, want = Tokenizer.from_file(path), []
    for i, t, *_ in rows():
        want.append((i, tuple(library.encode(t or "", add_special_tokens=False).ids + [2])))
    assert Counter((r.doc_id, tuple(np.frombuffer(r.ids, dtype="<u4").tolist())) for r in got) == Counter(want)
    order = sorted(got, key=lambda r: r.start)
    keys = [(r.doc_id is not None, r.doc_id or 0) for r in order]
    assert keys == sorted(keys)
    assert [r.start for r in order] == np.cumsum([0, *[r.n_tokens for r in order]])[:-1].tolist()
    one = next(r for r in got if r.doc_id == 10)
    hits = [f.find(10) for f in (token_files.TokenFile(r.path, dictionary) for r in files.collect())]
    assert [h.astype("<u4").tobytes() for h in hits if h is not None] == [bytes(one.ids)]
    with pytest.raises(ValueError):
        token_files.TokenFile(files.first().path, b"another")


def test_token_files_of_an_empty_table(spark):
    files, dictionary = token_files.write_token_files(documents(spark, []), work_path(spark, "t"), public_tokenizers.path("byte_bpe_50k.json"), end_id=2)
    assert token_files.read_token_files(files, dictionary).count() == 0


def test_quality_rules_base_counts(spark):
    for r in quality_rules.quality_rules(documents(spark)).select("text", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed", "kept").collect():
        text = r.text or ""
        w = re.findall(f"[^{SPACE}]+", text)
        lines = [x for x in text.split("\n") if re.search(f"[^{SPACE}]", x)]
        tri = Counter(zip(w, w[1:], w[2:]))
        hit = {j for k in range(len(w) - 2) if tri[tuple(w[k : k + 3])] > 1 for j in (k, k + 1, k + 2)}
        want = (len(w), sum(map(len, w)), sum(text.count(c) for c in "#*$%&|<>"), len(lines) - len(set(lines)), len(hit))
        assert tuple(r)[1:6] == want
        assert r.base_failed == (len(w) < 50 or 100 * len(hit) > 50 * len(w))
        assert not (r.base_failed and r.kept)


def test_quality_rules_verdict_against_plain_divergence(spark):
    docs = spark.read.parquet("/root/testdata/sf0.001/documents.parquet")
    got = {r.doc_id: r for r in quality_rules.quality_rules(docs).collect()}
    texts = {r.doc_id: (r.lang, r.text.encode()) for r in docs.collect()}
    kinds = {c: k for k, g in enumerate((b"abcdefghijklmnopqrstuvwxyz", b"ABCDEFGHIJKLMNOPQRSTUVWXYZ", b"0123456789", b" \t\n\v\f\r", b".,;:!?'\"()-")) for c in g}
    classes = lambda b: Counter(6 if x >= 0xC0 else kinds.get(x, 5) for x in b if not 0x80 <= x < 0xC0)
    by_class, by_word = defaultdict(Counter), defaultdict(Counter)
    for lang, b in texts.values():
        by_class[lang] += classes(b)
        by_word[lang].update(b.split())

    def far(p, q):
        sp, sq = sum(p.values()), sum(q.values())
        total = 0.0
        for k in {*p, *q}:
            a, b = p[k] / sp, q[k] / sq
            m = (a + b) / 2
            total += (a * np.log2(a / m) if a else 0) + (b * np.log2(b / m) if b else 0)
        return np.sqrt(max(total, 0) / 2)

    for i, (lang, b) in texts.items():
        n_all = by_word[lang].total()
        common = {w for w, n in by_word[lang].items() if n >= quality_rules.COMMON_SHARE * n_all}
        fold = lambda c: Counter({**{w: n for w, n in c.items() if w in common}, None: sum(n for w, n in c.items() if w not in common)})
        w = b.split()
        if len(w) < quality_rules.MIN_WORDS:
            assert got[i].class_distance is None
            continue
        d = far(classes(b), by_class[lang]), far(fold(Counter(w)), fold(by_word[lang]))
        assert np.allclose((got[i].class_distance, got[i].word_distance), d, atol=1e-9)
        assert got[i].kept == (not got[i].base_failed and d[0] <= quality_rules.MAX_CLASS_DISTANCE and d[1] <= quality_rules.MAX_WORD_DISTANCE)




@pytest.mark.parametrize("sent", [1_000, 2])
def test_quality_rules_of_rare_languages(spark, monkeypatch, sent):
    """A rare language with enough words has its own reference, whether it is sent along or joined; null and thin ones have none."""
    import random

    monkeypatch.setattr(quality_rules, "SENT_LANGUAGES", sent)
    rnd = random.Random(2)
    text = lambda letters, n: " ".join("".join(rnd.choice(letters) for _ in range(rnd.randint(2, 7))) for _ in range(n))
    latin, cyrillic, greek = "abcdefghij", "абвгдежзик", "αβγδεζηθικ"
    docs = [("en", text(latin, 40_000)) for _ in range(60)]
    docs += [(lang, text(letters, 100)) for lang, letters in (("cy", cyrillic), ("la", latin), ("gr", greek)) for _ in range(21)]
    docs += [("thin", text(cyrillic, 100)), (None, text(greek, 100)), (None, text(latin, 100)), ("gr", text(latin, 100))]
    table = spark.createDataFrame([(k, *d) for k, d in enumerate(docs)], "doc_id long, lang string, text string").repartition(4)
    got = sorted(quality_rules.quality_rules(table).collect())
    assert [(r.doc_id, r.lang) for r in got] == [(k, d[0]) for k, d in enumerate(docs)]
    assert [r.doc_id for r in got if not r.kept] == [len(docs) - 1]
    assert {r.lang for r in got if r.class_distance is None} == {"thin", None}
    assert max(r.class_distance for r in got[:-4]) < 0.2


def test_bpe_splits_around_every_code_point_as_the_library(spark):
    tokens = bpe.load_ranks(public_tokenizers.path(MULTI))
    library = tiktoken.Encoding("x", pat_str=public_tokenizers.PATTERN, mergeable_ranks={t: i for i, t in enumerate(tokens) if t}, special_tokens={})
    replay = bpe.MergeReplay(tokens)
    encoder = bpe.TextEncoder(public_tokenizers.PATTERN, lambda words: replay.encode([w.encode() for w in words]), remembered=0)
    points = [chr(c) for c in range(0x110000) if not 0xD800 <= c < 0xE000]
    for at in range(0, len(points), 40_000):
        texts = ["".join(f"x{c}y {c} 1{c}2\n{c}{c}'s" for c in points[k : k + 1000]) for k in range(at, min(at + 40_000, len(points)), 1000)]
        for text, ids in zip(texts, encoder.block(texts)):
            assert np.frombuffer(ids, dtype="<u4").tolist() == library.encode_ordinary(text)


def test_jaccard_join_leaves_only_what_its_result_reads(spark, tmp_path, monkeypatch):
    from sizeprofile.llm import common

    monkeypatch.setattr(common, "shared_root", lambda spark: f"file://{tmp_path}")
    got = jaccard_join.jaccard_components(documents(spark), 80, 5)
    assert sorted(p.name.rpartition("-")[0] for p in tmp_path.iterdir()) == ["sizeprofile-node-components", "sizeprofile-prefixes"]
    assert got.count() == len(rows())


def test_jaccard_kernels_hold_bounded_memory():
    import tracemalloc

    import pyarrow as pa

    from sizeprofile.llm import common

    rng = np.random.default_rng(3)
    sets = [np.unique(rng.integers(0, 3000, 500, dtype=np.uint64)) for _ in range(60)]
    for room in (7, 1000, 1 << 20):
        repeats, parts = jaccard_join.Repeats(room), []
        for s in sets:
            parts += repeats.add(s)
        every = np.concatenate(sets)
        for k, (values, counts) in enumerate([*parts, repeats.flush()]):
            v, c = np.unique(every[k * room : (k + 1) * room], return_counts=True)
            assert values.tolist() == v[c > 1].tolist() and counts.tolist() == c[c > 1].tolist()
    tracemalloc.start()
    repeats = jaccard_join.Repeats(1 << 20)
    for _ in range(9000):  # the sets of a task's texts, 8,192 of which had been held and sorted as a copy
        for _ in repeats.add(rng.integers(0, 1 << 60, 300, dtype=np.uint64)):
            pass
    assert tracemalloc.get_traced_memory()[1] < 2 * repeats.buffer.nbytes
    tracemalloc.stop()
    batch = pa.RecordBatch.from_arrays([pa.array(range(50)), pa.array(["x" * (k * k * 10) for k in range(50)])], names=["k", "text"])
    parts = list(common.slices(batch, 20_000))
    assert sum((p.column(0).to_pylist() for p in parts), []) == list(range(50))
    assert all(p.nbytes <= 50_000 or p.num_rows == 1 for p in parts)
    seen = []
    assert list(common.lean(lambda bs: (seen.append(b.num_rows) or b for b in bs))([pa.RecordBatch.from_arrays([pa.array(["y" * (3 << 20)] * 5)], names=["t"])])) and max(seen) <= 2
