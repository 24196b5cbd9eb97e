"""Byte-level BPE encoding by corpus-level merge replay, and decoding."""

from __future__ import annotations

import base64
import hashlib
import heapq
from itertools import filterfalse

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import file_store, free_name, kept_in_process

#: Distinct words whose ids a worker process keeps from block to block; others are encoded anew in each block.
REMEMBERED_WORDS = 300_000
#: Bytes of text in one replay block; a longer document makes a block of its own.
BLOCK_BYTES = 3 << 20


def load_ranks(path: str) -> list[bytes]:
    """The tokens of a rank file (base64 token and rank per line), by rank. Read on the driver: a vocabulary is bounded."""
    store, at = file_store(path)
    with store.open_input_stream(at) as f:
        pairs = [line.split() for line in f.read().splitlines() if line.strip()]
    out = [b""] * (max(int(r) for _, r in pairs) + 1)
    for token, rank in pairs:
        out[int(rank)] = base64.b64decode(token)
    return out


class MergeReplay:
    """Encodes many distinct words at once.

    All words lie in one array of token ids with links to the left and right neighbour. An inverted index holds, for
    each pair that forms a token, the positions where it stands. Pairs are replayed in the order of the rank of the
    token they form; a merge touches only its two neighbours and files the new pairs in the index.

    A merge may form a pair of lower rank than the one being replayed (a token need not be built from lower ranks
    on both sides). The rest of that word's positions then goes back into the index, so each word sees its merges in
    exactly the order in which encoding it alone would make them.
    """

    def __init__(self, tokens: list[bytes]):
        self.rank = {t: i for i, t in enumerate(tokens) if t}
        single = [self.rank.get(bytes([b]), -1) for b in range(256)]
        if min(single) < 0:
            raise ValueError("a byte-level vocabulary must hold all 256 single bytes")
        self.single = np.array(single, dtype=np.int64)
        #: Token formed by a pair, for every way to cut a token in two tokens; the key holds both ids.
        self.formed: dict[int, int] = {}
        for t, i in self.rank.items():
            for cut in range(1, len(t)):
                if (a := self.rank.get(t[:cut])) is not None and (b := self.rank.get(t[cut:])) is not None:
                    self.formed[a << 32 | b] = i

    def _first_pairs(self, ids: np.ndarray, right: np.ndarray) -> dict[int, list[int]]:
        """The inverted index of all neighbouring single bytes, by sorting instead of one by one."""
        at = np.flatnonzero(right >= 0)
        keys = ids[at] << 32 | ids[right[at]]
        order = np.argsort(keys, kind="stable")
        keys, at = keys[order], at[order]
        begins = np.flatnonzero(np.r_[True, keys[1:] != keys[:-1]]) if len(keys) else np.zeros(0, dtype=np.int64)
        ends = [*begins[1:].tolist(), len(keys)]
        formed = self.formed
        return {k: at[b:e].tolist() for k, b, e in zip(keys[begins].tolist(), begins.tolist(), ends) if k in formed}

    def encode(self, words: list[bytes]) -> list[bytes]:
        """For each word its ids as little-endian unsigned 32-bit integers."""
        out: list[bytes | None] = [None if (w := self.rank.get(x)) is None else w.to_bytes(4, "little") for x in words]
        rest = [k for k, x in enumerate(out) if x is None]  # a word that is a token stands for itself
        parts = [words[k] for k in rest]
        sizes = np.array([len(w) for w in parts], dtype=np.int64)
        start = self.single[np.frombuffer(b"".join(parts), dtype=np.uint8)]
        owner = np.repeat(np.arange(len(parts)), sizes)
        n = len(start)
        ends = np.cumsum(sizes)
        right = np.arange(1, n + 1)
        left = np.arange(-1, n - 1)
        filled = sizes > 0
        right[ends[filled] - 1] = -1
        left[(ends - sizes)[filled]] = -1
        index = self._first_pairs(start, right)
        formed = self.formed
        heap = [(formed[k], k) for k in index]
        heapq.heapify(heap)
        ids, left, right, word = start.tolist(), left.tolist(), right.tolist(), owner.tolist()
        push, pop, form, places_of = heapq.heappush, heapq.heappop, formed.get, index.get
        while heap:
            token, key = pop(heap)
            places = index.pop(key)
            a, b = key >> 32, key & 0xFFFFFFFF
            if len(places) > 1:
                places.sort()
            waits, again = -1, []
            for at in places:
                if ids[at] != a or (after := right[at]) < 0 or ids[after] != b:
                    continue
                if word[at] == waits:  # a lower rank came up in this word: it goes first
                    again.append(at)
                    continue
                ids[at], ids[after] = token, -1
                right[at] = nxt = right[after]
                right[after] = -1
                if nxt >= 0:
                    left[nxt] = at
                    made = form(k := token << 32 | ids[nxt])
                    if made is not None:
                        if (held := places_of(k)) is None:
                            index[k] = [at]
                            push(heap, (made, k))
                        else:
                            held.append(at)
                        if made < token:
                            waits = word[at]
                if (prev := left[at]) >= 0:
                    made = form(k := ids[prev] << 32 | token)
                    if made is not None:
                        if (held := places_of(k)) is None:
                            index[k] = [prev]
                            push(heap, (made, k))
                        else:
                            held.append(prev)
                        if made < token:
                            waits = word[at]
            if again:
                if (held := places_of(key)) is None:
                    index[key] = again
                    push(heap, (token, key))
                else:
                    held += again
        final = np.array(ids, dtype=np.int64)
        live = final >= 0
        raw = final[live].astype("<u4").tobytes()
        begin = 0
        for k, end in zip(rest, np.searchsorted(owner[live], np.arange(len(parts)), side="right").tolist()):
            out[k] = raw[4 * begin : 4 * end]
            begin = end
        return out  # type: ignore[return-value]


#: The split that both vocabularies here use (fixed value).
BYTE_LEVEL_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


#: Stands, while a text is split, for a code point that is no letter or number to the library. Private use: no class of its own.
_NEITHER = "\ue000"


class Splitter:
    """Splits a text by a pattern. For the byte-level split there is an equal, faster expression for texts that hold
    only ASCII, Latin letters and common punctuation; all other texts take the general one.

    The `regex` module's tables may be newer than the library's: code points that only the module calls letters or
    numbers (the library tells by a probe) are hidden from the split, and the pieces are cut from the text itself.
    """

    def __init__(self, pattern: str):
        import re
        import sys

        import regex
        import tiktoken

        plain = regex.compile(pattern).findall
        every = "".join(map(chr, [*range(0xD800), *range(0xE000, sys.maxunicode + 1)]))
        probe = tiktoken.Encoding("classes", pat_str=r"[\p{L}\p{N}]", mergeable_ranks={bytes([b]): b for b in range(256)}, special_tokens={})
        known = bytes(probe.encode_ordinary(every)).decode()  # what its pattern does not match, the library leaves out
        new = set().union(*regex.findall(r"[\p{L}\p{N}]+", every)).difference(known)
        hide = dict.fromkeys(map(ord, new), _NEITHER)

        def general(text: str) -> list[str]:
            if new.isdisjoint(text):
                return plain(text)
            return [text[m.start() : m.end()] for m in regex.finditer(pattern, text.translate(hide))]

        self.general = general
        letters = "A-Za-z\u00c0-\u00d6\u00d8-\u00f6\u00f8-\u02af"
        self.latin = re.compile(rf" ?[{letters}]+|'(?:[stmd]|re|ve|ll)| ?[0-9]+| ?[^\s{letters}0-9]+|\s+(?!\S)|\s+").findall
        self.other = re.compile(rf"[^\t-\r -~{letters}\u2010-\u2027\u2030-\u205e]").search if pattern == BYTE_LEVEL_SPLIT else lambda text: True

    def __call__(self, text: str) -> list[str]:
        return self.general(text) if self.other(text) else self.latin(text)


class TextEncoder:
    """Texts to ids: splits by the pattern, encodes the distinct unknown words of a block together, joins the words' ids."""

    def __init__(self, pattern: str, encode_words, remembered: int = REMEMBERED_WORDS):
        self.split = Splitter(pattern)
        self.encode_words = encode_words
        self.remembered = remembered
        self.known: dict[str, bytes] = {}

    def block(self, texts: list[str]) -> list[bytes]:
        known, pieces, fresh = self.known, [self.split(t) for t in texts], set()
        for p in pieces:
            fresh.update(filterfalse(known.__contains__, p))
        new = list(fresh)
        table = dict(zip(new, self.encode_words(new)))
        if len(known) + len(table) <= self.remembered:
            known.update(table)
            return [b"".join(map(known.__getitem__, p)) for p in pieces]
        both = ChainedLookup(known)
        both.update(table)
        return [b"".join(map(both.__getitem__, p)) for p in pieces]


class ChainedLookup(dict):
    """A table with another one behind it."""

    def __init__(self, behind: dict):
        self.behind = behind

    def __missing__(self, key):
        return self.behind[key]


def text_blocks(batches, column: str, most: int = BLOCK_BYTES):
    """(batch, texts) slices whose texts hold at most `most` bytes, one row at least."""
    for batch in batches:
        col = batch.column(batch.schema.get_field_index(column))
        sizes = np.diff(np.frombuffer(col.buffers()[1], dtype=np.int64 if pa.types.is_large_binary(col.type) or pa.types.is_large_string(col.type) else np.int32)[col.offset : col.offset + len(col) + 1]) if len(col) else np.zeros(0, dtype=np.int64)
        begin, held = 0, 0
        for i, size in enumerate(sizes.tolist()):
            if held and held + size > most:
                yield batch.slice(begin, i - begin), col.slice(begin, i - begin)
                begin, held = i, 0
            held += size
        if begin < len(col):
            yield batch.slice(begin), col.slice(begin)


def bpe_encode(docs: DataFrame, vocab_path: str, pattern: str, text_col: str = "text", ids_col: str = "ids") -> DataFrame:
    """Add `ids_col`: the text's token ids as little-endian unsigned 32-bit integers (binary).

    A null or empty text has empty ids. Every row is encoded by itself, so repeated rows and ids get equal results.
    An input column named like `ids_col` is replaced.

    The replay runs over blocks of a task's rows (BLOCK_BYTES of text): a table of the distinct words of the whole
    corpus would have to be shuffled and joined back to every word occurrence, several times the size of the input.
    """
    tokens = load_ranks(vocab_path)
    digest = hashlib.sha256(b"\n".join(tokens)).hexdigest()
    docs = docs.drop(ids_col)
    raw = free_name(docs.columns, "text_bytes")
    fed = docs.withColumn(raw, F.coalesce(F.col(f"`{text_col}`"), F.lit("")))
    schema = docs.withColumn(ids_col, F.lit(b"")).schema
    keep = docs.columns

    def run(batches):
        encoder = kept_in_process(("bpe", pattern, digest), lambda: TextEncoder(pattern, (lambda replay: lambda words: replay.encode([w.encode() for w in words]))(MergeReplay(tokens))))
        for batch, texts in text_blocks(batches, raw):
            ids = encoder.block(texts.to_pylist())
            arrays = [batch.column(batch.schema.get_field_index(c)) for c in keep]
            yield pa.RecordBatch.from_arrays([*arrays, pa.array(ids, type=pa.binary())], names=[*keep, ids_col])

    return fed.mapInArrow(run, schema)


def bpe_decode(encoded: DataFrame, vocab_path: str, ids_col: str = "ids", out_col: str = "decoded") -> DataFrame:
    """Add `out_col`: the bytes of the tokens of `ids_col` (null: empty). Bytes need not be valid UTF-8."""
    tokens = load_ranks(vocab_path)
    encoded = encoded.drop(out_col)
    schema = encoded.withColumn(out_col, F.lit(b"")).schema
    keep = encoded.columns

    def run(batches):
        get = tokens.__getitem__
        for batch in (b.slice(i, 500) for b in batches for i in range(0, b.num_rows, 500)):
            col = batch.column(batch.schema.get_field_index(ids_col))
            texts = [b"".join(map(get, np.frombuffer(x or b"", dtype="<u4").tolist())) for x in col.to_pylist()]
            yield pa.RecordBatch.from_arrays([*batch.columns, pa.array(texts, type=pa.binary())], names=[*keep, out_col])

    return encoded.mapInArrow(run, schema)


def op8_bpe(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    path = public_tokenizers.path("byte_bpe_multi_50k.tiktoken")
    encoded = bpe_encode(docs, path, public_tokenizers.PATTERN).select("doc_id", "ids")
    decoded = bpe_decode(encoded, path)
    return decoded.select("doc_id", F.expr("octet_length(ids) div 4").cast("long").alias("n_tokens"), F.sha2("ids", 256).alias("ids_sha256"), F.sha2("decoded", 256).alias("decoded_sha256"))
