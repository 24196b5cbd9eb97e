"""Token-id files: zstandard frames with a shared dictionary, one per document, with an offset index.

File layout (integers little-endian)::

    magic (8)  SHA-256 of the dictionary (32)
    one zstandard frame per document: its ids as unsigned integers of `width` bytes
    index: document ids int64[n], null flags uint8[n], first id uint64[n], frame offset uint64[n], frame bytes uint32[n], ids uint32[n]
    footer: index offset, documents, ids (uint64 each), width (uint8), magic (8)

The index gives any document by two reads: its entry and its frame. The dictionary lies beside the files under its hash.
"""

from __future__ import annotations

import hashlib
import math
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import Window

from .bpe import BYTE_LEVEL_SPLIT, REMEMBERED_WORDS, Splitter, text_blocks
from .common import batches_of, file_store, kept_in_process, put_file, rows_of, work_path, written

MAGIC = b"SPTOKEN1"
_FOOTER = "<QQQB8s"
_INDEX = (("id", "<i8"), ("null", "u1"), ("start", "<u8"), ("at", "<u8"), ("size", "<u4"), ("n", "<u4"))
#: Documents and text bytes aimed at in one file; a file is closed at twice that.
FILE_BYTES, FILE_DOCS = 32 << 20, 200_000
#: Ranges of ids at most: their bounds go to every task, and their totals to the driver.
MOST_RANGES = 4096
#: The dictionary and the bounded sample of documents (whole, at most SAMPLE_BYTES each) from which it is trained.
DICT_BYTES, SAMPLE_DOCS, SAMPLE_BYTES = 64 << 10, 1_000, 64 << 10
#: Code points outside this set are classed alike by all Unicode versions in use (letters added lately in the basic plane); with the
#: planes above, texts holding them are split by the tokenizers library itself.
_RECENT = re.compile("[՘֋֌࢏౜೜₏₝-₟꟎-꟱꭬꭭\U00010000-\U0010ffff]")


def _byte_letters() -> dict[int, str]:
    """The letter by which a byte-level vocabulary writes each byte: itself if printable, else the next one from 256 on."""
    printable = {*range(33, 127), *range(161, 173), *range(174, 256)}
    out, free = {}, 256
    for b in range(256):
        out[b] = chr(b) if b in printable else chr(free)
        free += b not in printable
    return out


class _Words(dict):
    """Word to serialised ids; the library's model encodes a word when it is first met, and `most` words are kept."""

    def __init__(self, model, most: int):
        self.tokenize, self.most, self.letters = model.tokenize, most, _byte_letters()

    def __missing__(self, word: str) -> bytes:
        ids = b"".join([t.id.to_bytes(4, "little") for t in self.tokenize(word.encode().decode("latin-1").translate(self.letters))])
        if len(self) < self.most:
            self[word] = ids
        return ids


class LibraryEncoder:
    """Texts to ids by the tokenizers library.

    The text is split as the library's byte-level step would, and its model encodes each distinct word once. Texts with
    a special token, or with code points that not all Unicode versions class alike, go through the whole library.
    """

    def __init__(self, definition: str, remembered: int = REMEMBERED_WORDS):
        import os

        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.library = Tokenizer.from_str(definition)
        self.special = [t.content for t in self.library.get_added_tokens_decoder().values()]
        self.split = Splitter(BYTE_LEVEL_SPLIT)
        self.words = _Words(self.library.model, remembered)

    def encode(self, text: str) -> bytes:
        odd = self.split.other(text)
        if (odd and _RECENT.search(text)) or any(s in text for s in self.special):
            return np.array(self.library.encode(text, add_special_tokens=False).ids, dtype="<u4").tobytes()
        return b"".join(map(self.words.__getitem__, self.split.general(text) if odd else self.split.latin(text)))

    def block(self, texts: list[str]) -> list[bytes]:
        return [self.encode(t) for t in texts]


def _definition(tokenizer_path: str) -> str:
    store, at = file_store(tokenizer_path)
    with store.open_input_stream(at) as f:
        return f.read().decode()


def train_dictionary(samples: list[bytes], size: int = DICT_BYTES) -> bytes:
    """A zstandard dictionary of the sampled serialised id arrays; empty (plain frames) if there are too few to train on."""
    import zstandard

    samples = [s for s in samples if len(s) >= 8]
    try:
        return zstandard.train_dictionary(size, samples).as_bytes() if len(samples) >= 8 else b""
    except zstandard.ZstdError:
        return b""


def _zdict(raw: bytes):
    import zstandard

    return zstandard.ZstdCompressionDict(raw) if raw else None


class _Writer:
    """One file: frames go out as they come; only the index stays in memory."""

    def __init__(self, out, dict_hash: bytes, width: int):
        self.out, self.width, self.rows, self.ids, self.at = out, width, [], 0, len(MAGIC) + len(dict_hash)
        out.write(MAGIC + dict_hash)

    def add(self, doc_id: int | None, n: int, frame: bytes) -> None:
        self.rows.append((doc_id or 0, doc_id is None, self.ids, self.at, len(frame), n))
        self.out.write(frame)
        self.ids += n
        self.at += len(frame)

    def close(self) -> None:
        cols = list(zip(*self.rows)) or [()] * len(_INDEX)
        for col, (_, kind) in zip(cols, _INDEX):
            self.out.write(np.array(col, dtype=kind).tobytes())
        self.out.write(struct.pack(_FOOTER, self.at, len(self.rows), self.ids, self.width, MAGIC))


class TokenFile:
    """Random and sequential access to one file."""

    def __init__(self, path: str, dictionary: bytes):
        import zstandard

        store, at = file_store(path)
        self.f = store.open_input_file(at)
        size = self.f.size()
        self.f.seek(size - struct.calcsize(_FOOTER))
        self.index_at, self.n_docs, self.n_ids, self.width, magic = struct.unpack(_FOOTER, self.f.read(struct.calcsize(_FOOTER)))
        self.f.seek(0)
        head = self.f.read(len(MAGIC) + 32)
        if magic != MAGIC or head[: len(MAGIC)] != MAGIC:
            raise ValueError(f"{path} is no token file")
        if head[len(MAGIC) :] != hashlib.sha256(dictionary).digest():
            raise ValueError(f"{path} was written with another dictionary")
        self.f.seek(self.index_at)
        raw, self.index, begin = self.f.read(size - struct.calcsize(_FOOTER) - self.index_at), {}, 0
        for name, kind in _INDEX:
            self.index[name] = np.frombuffer(raw, dtype=kind, count=self.n_docs, offset=begin)
            begin += self.index[name].nbytes
        self.unpack = zstandard.ZstdDecompressor(dict_data=_zdict(dictionary)).decompress

    def ids(self, k: int, frame: bytes | None = None) -> np.ndarray:
        """The ids of the k-th document."""
        n, at, size = (int(self.index[x][k]) for x in ("n", "at", "size"))
        if frame is None:
            self.f.seek(at)
            frame = self.f.read(size)
        return np.frombuffer(self.unpack(frame, max_output_size=max(1, n * self.width)), dtype=f"<u{self.width}").astype("<u4")

    def find(self, doc_id: int) -> np.ndarray | None:
        """The ids of a document by its id (the first of several), by binary search in the index."""
        nulls = int(self.index["null"].sum())
        k = nulls + int(np.searchsorted(self.index["id"][nulls:], doc_id))
        return self.ids(k) if k < self.n_docs and self.index["id"][k] == doc_id else None

    def scan(self, chunk: int = 8 << 20):
        """(doc_id, first id, ids) of all documents, with sequential reads of about `chunk` bytes."""
        at, size, k = self.index["at"], self.index["size"], 0
        while k < self.n_docs:
            end = max(k + 1, int(np.searchsorted(at, at[k] + np.uint64(chunk))))
            base = int(at[k])
            self.f.seek(base)
            raw = self.f.read(int(at[end - 1]) + int(size[end - 1]) - base)
            for i in range(k, end):
                b = int(at[i]) - base
                yield None if self.index["null"][i] else int(self.index["id"][i]), int(self.index["start"][i]), self.ids(i, raw[b : b + int(size[i])])
            k = end


_FILES = pa.schema([("shard", pa.int32()), ("part", pa.int32()), ("path", pa.string()), ("n_docs", pa.int64()), ("n_ids", pa.int64()), ("n_bytes", pa.int64())])


def write_token_files(docs: DataFrame, folder: str, tokenizer_path: str, end_id: int | None, id_col: str = "doc_id", text_col: str = "text", file_bytes: int = FILE_BYTES) -> tuple[DataFrame, bytes]:
    """Write all documents in ascending order of id; return (the list of files, the dictionary).

    A null text is empty (its ids are the end id alone). Null ids come first, ties in the order of their frames, each
    row a document of its own. Ranges of ids, MOST_RANGES at any size, are cut at quantiles of the id column, so that only
    compressed frames are shuffled, once, and sorted inside each range; a range's task starts a new file at twice the
    aimed size, also inside a hot id. Files are renamed into place when complete and listed only by the task attempt that succeeded.
    """
    import zstandard

    spark = docs.sparkSession
    definition = _definition(tokenizer_path)
    rows = rows_of(docs, id=F.col(f"`{id_col}`").cast("long"), text=F.coalesce(F.col(f"`{text_col}`"), F.lit("")))
    n_docs, n_bytes = rows.agg(F.count(F.lit(1)), F.coalesce(F.sum(F.octet_length("text")), F.lit(0))).first()
    shards = min(MOST_RANGES, max(1, math.ceil(n_bytes / file_bytes), math.ceil(n_docs / FILE_DOCS)))
    cuts = sorted({int(x) for x in rows.approxQuantile("id", [k / shards for k in range(1, shards)], 0.2 / shards)}) if shards > 1 else []
    share = min(1.0, 1.2 * SAMPLE_DOCS / max(1, n_docs))
    picked = rows.where((F.octet_length("text") <= SAMPLE_BYTES) & (F.pmod(F.xxhash64("id"), F.lit(1_000_000)) < int(share * 1_000_000) + 1))
    sample = [r.text for r in picked.select("text").limit(SAMPLE_DOCS).collect()]
    encoder = LibraryEncoder(definition)
    width = 2 if encoder.library.get_vocab_size(with_added_tokens=True) <= 65536 and (end_id or 0) < 65536 else 4
    end = b"" if end_id is None else end_id.to_bytes(4, "little")

    def packed(ids: bytes) -> bytes:
        return np.frombuffer(ids + end, dtype="<u4").astype(f"<u{width}").tobytes()

    dictionary = train_dictionary([packed(x) for x in encoder.block(sample)])
    dict_hash = hashlib.sha256(dictionary).digest()
    put_file(folder, f"dict-{dict_hash.hex()}.zdict", lambda out: out.write(dictionary))

    def encode(batches):
        own = kept_in_process(("library", definition), lambda: LibraryEncoder(definition))
        bounds = np.array(cuts, dtype=np.int64)
        shared = _zdict(dictionary)
        if shared:
            shared.precompute_compress(level=3)
        pack = zstandard.ZstdCompressor(level=3, dict_data=shared).compress
        for batch, texts in text_blocks(batches, "text"):
            raw = [packed(x) for x in own.block(texts.to_pylist())]
            ids = batch.column(0)
            shard = np.searchsorted(bounds, ids.fill_null(-(2**63)).to_numpy(zero_copy_only=False), side="right").astype(np.int32)
            yield pa.RecordBatch.from_arrays([pa.array(shard), ids, pa.array([len(x) // width for x in raw], type=pa.int32()), pa.array(map(pack, raw), type=pa.binary())], names=["shard", "id", "n", "frame"])

    def write(batches):
        def one():
            rows = ((s, i, n, f) for b in batches for s, i, n, f in zip(*(c.to_pylist() for c in b.columns)))
            row = next(rows, None)
            shard, part = None, 0
            while row:
                shard, part = row[0], part + 1 if shard == row[0] else 0

                def body(out, shard=shard):
                    nonlocal row, done
                    w = _Writer(out, dict_hash, width)
                    while row and row[0] == shard and w.at < 2 * file_bytes and len(w.rows) < 2 * FILE_DOCS:
                        w.add(*row[1:])
                        row = next(rows, None)
                    w.close()
                    done = (len(w.rows), w.ids, w.at)

                done = None
                path = put_file(folder, f"part-{shard:06d}-{part:04d}-{zlib.crc32(repr(row[:3]).encode()):08x}.tok", body)
                yield (shard, part, path, *done)

        yield from batches_of(_FILES, one())

    frames = rows.mapInArrow(encode, "shard int, id long, n int, frame binary")
    dealt = frames.repartitionById(shards, F.col("shard")).sortWithinPartitions("shard", F.col("id").asc_nulls_first(), "n", "frame")
    files = written(dealt.mapInArrow(write, "shard int, part int, path string, n_docs long, n_ids long, n_bytes long"), "token-files")
    return files, dictionary


def read_token_files(files: DataFrame, dictionary: bytes) -> DataFrame:
    """doc_id, start (ids of all documents before it), n_tokens, ids (little-endian unsigned 32-bit) of all documents of the files."""
    totals, shard_base, held = files.groupBy("shard").agg(F.sum("n_ids").alias("n")).collect(), {}, 0  # MOST_RANGES rows at most
    for r in sorted(totals, key=lambda r: r.shard):
        shard_base[r.shard], held = held, held + r.n
    before = Window.partitionBy("shard").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    starts = F.broadcast(files.sparkSession.createDataFrame(list(shard_base.items()), "shard int, first long"))
    based = files.join(starts, "shard").select("path", (F.col("first") + F.coalesce(F.sum("n_ids").over(before), F.lit(0))).alias("base"))
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids", pa.binary())])

    def read(batches):
        def rows():
            for b in batches:
                for path, base in zip(*(c.to_pylist() for c in b.columns)):
                    for doc_id, start, ids in TokenFile(path, dictionary).scan():
                        yield doc_id, base + start, len(ids), ids.tobytes()

        yield from batches_of(schema, rows(), weigh=lambda r: len(r[3]))

    n = max(1, files.count())
    return based.repartition(n).mapInArrow(read, "doc_id long, start long, n_tokens long, ids binary")


def op3_token_files(spark, sf_dir: str) -> DataFrame:
    import public_tokenizers

    docs = spark.read.parquet(f"{sf_dir}/documents.parquet").select("doc_id", "text")
    files, dictionary = write_token_files(docs, work_path(spark, "tokens"), public_tokenizers.path("byte_bpe_50k.json"), end_id=2)
    return read_token_files(files, dictionary).select("doc_id", "start", "n_tokens", F.crc32("ids").alias("ids_crc32"))
