"""Token-id output: independent zstandard frames, a trailing seek table, and a checksum for every frame.

A shard file holds whole documents in id order.  Each frame is a self-contained zstandard frame of a few documents:
a count, their ids and lengths, then their token ids as little-endian unsigned integers of two or four bytes.  The file
ends in two skippable frames: a directory of the first and last document id of every frame, and a seek table in the
public seekable layout, with the compressed size, raw size and checksum (low 32 bits of XXH64 of the raw bytes) of every
frame.  A reader fetches both from the end of the file and decompresses only the frames of the documents it wants.

Defined results: null text counts as empty, and an empty document is just the end id; null ids sort first; repeated
ids follow each other in the order of their texts' hashes; an empty table writes no file and gives no rows; extra columns
are ignored.
"""

from __future__ import annotations

import itertools
import re
import struct
import zlib

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
import zstandard
from pyspark import TaskContext
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from paircuration.llm.common import pieces, scratch

# Fixed values of the seekable zstandard layout: skippable-frame magic, footer magic, descriptor with the checksum bit.
SKIPPABLE, FOOTER, CHECKSUMS = 0x184D2A5E, 0x8F92EAB1, 0x80
DIRECTORY = 0x184D2A5D  # another skippable-frame magic, ours for the directory
FRAME_TOKENS = 1 << 18
NO_ID = -(1 << 63)
_CACHE_WORDS = 1_000_000
# Letters a-z and Latin-1 (UTF-8 lead byte C3 but for its two signs), then ASCII marks without the apostrophe.
_LETTERS_MARKS = re.compile(rb"((?:[A-Za-z]|\xc3[\x80-\x96\x98-\xb6\xb8-\xbf])+)([!-&(-/:-@\[-`{-~]+)")


class CachedEncoder:
    """Token ids of whole texts, chunk by white-space chunk.

    Valid for tokenizers that never join across ASCII white space and drop it.  Each distinct chunk is encoded once
    while it stays in a bounded cache; the ids of a batch are then gathered by array arithmetic.  A full cache keeps its
    oldest half: common chunks come early.
    """

    def __init__(self, path: str):
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_file(path)
        self.dtype = np.uint16 if self.tokenizer.get_vocab_size(with_added_tokens=True) <= 1 << 16 else np.uint32
        marks = [(i, t) for i, t in self.tokenizer.get_added_tokens_decoder().items() if t.special and not (t.lstrip or t.rstrip or t.single_word)]
        self.mark = max(marks, default=(None, None), key=lambda m: m[0])
        self.lowers = self.tokenizer.normalizer is not None and self.tokenizer.normalizer.normalize_str("AZ") == "az"
        self.slots: dict[bytes, int] = {}
        self.pending: list[tuple[np.ndarray, np.ndarray]] = []
        self.flat, self.at = np.zeros(0, dtype=self.dtype), np.zeros(1, dtype=np.int64)

    def _shrink(self) -> None:
        keep = _CACHE_WORDS // 2
        self.slots = dict(itertools.islice(self.slots.items(), keep))
        self.at = self.at[: keep + 1].copy()
        self.flat = self.flat[: self.at[-1]].copy()

    def _learn(self, units: list[bytes]) -> None:
        """Encode units and append them; many share a call, told apart by a special token between them."""
        number, token = self.mark
        for i in range(0, len(units), 256):
            words = [w.decode() for w in units[i : i + 256]]
            ids, cuts = None, ()
            if token is not None:
                ids = np.array(self.tokenizer.encode_batch_fast([token.content.join(words)], add_special_tokens=False)[0].ids, dtype=self.dtype)
                cuts = np.flatnonzero(ids == number)
            if ids is not None and len(cuts) == len(words) - 1:
                sizes = np.diff(np.concatenate([[-1], cuts, [len(ids)]])) - 1
                ids = ids[ids != number]
            else:
                coded = [c.ids for c in self.tokenizer.encode_batch_fast(words, add_special_tokens=False)]
                sizes, ids = np.fromiter(map(len, coded), np.int64, len(coded)), np.array(list(itertools.chain.from_iterable(coded)), dtype=self.dtype)
            self._append(units[i : i + 256], sizes, ids)
        self._pack()

    def _append(self, units: list[bytes], sizes: np.ndarray, ids: np.ndarray) -> None:
        self.slots.update(zip(units, range(len(self.slots), len(self.slots) + len(units))))
        self.pending.append((sizes, ids))

    def _pack(self) -> None:
        if self.pending:
            self.flat = np.concatenate([self.flat, *(p[1] for p in self.pending)])
            self.at = np.concatenate([self.at, self.at[-1] + np.cumsum(np.concatenate([p[0] for p in self.pending]))])
            self.pending = []

    def _gather(self, rows: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """(ids laid end to end, running sizes) of cached units."""
        first = self.at[rows]
        sizes = self.at[rows + 1] - first
        upto = np.concatenate([[0], np.cumsum(sizes)])
        return self.flat[np.repeat(first - upto[:-1], sizes) + np.arange(upto[-1])], upto

    def _add(self, fresh: list[bytes]) -> None:
        """A chunk of plain letters and a run of marks is put together from both; any other chunk is encoded itself."""
        split = [_LETTERS_MARKS.fullmatch(w) for w in fresh]
        pairs = [(w, m) for w, m in zip(fresh, split) if m]
        units = dict.fromkeys(w for w, m in zip(fresh, split) if not m)
        units.update(dict.fromkeys(u for _, m in pairs for u in m.groups() if u not in self.slots))
        self._learn(list(units))
        if pairs:
            rows = np.fromiter((self.slots[u] for _, m in pairs for u in m.groups()), np.int64, 2 * len(pairs))
            ids, upto = self._gather(rows)
            self._append([w for w, _ in pairs], np.diff(upto[::2]), ids)
            self._pack()

    def encode(self, texts: list[bytes], end_id: int) -> list[np.ndarray]:
        """Ids of each text, its end id included."""
        if len(self.slots) > _CACHE_WORDS:
            self._shrink()
        # the tokenizer lower-cases; a text that may name a special token keeps its case
        chunked = [(t if not self.lowers or b"<|" in t else t.lower()).split() for t in texts]
        words = list(itertools.chain.from_iterable(chunked))
        rows = np.fromiter(map(self.slots.get, words, itertools.repeat(-1)), np.int64, len(words))
        missing = np.flatnonzero(rows < 0)
        if len(missing):
            lacking = [words[i] for i in missing.tolist()]
            self._add(list(dict.fromkeys(lacking)))
            rows[missing] = np.fromiter(map(self.slots.__getitem__, lacking), np.int64, len(lacking))
        ids, upto = self._gather(rows)
        ends = upto[np.cumsum(np.fromiter(map(len, chunked), np.int64, len(chunked)))]
        return np.split(np.insert(ids, ends, end_id), (ends + np.arange(1, len(ends) + 1))[:-1])


_encoders: dict[str, CachedEncoder] = {}


def encoder(path: str) -> CachedEncoder:
    if path not in _encoders:
        _encoders[path] = CachedEncoder(path)
    return _encoders[path]


class FrameWriter:
    """Appends documents to a shard file."""

    def __init__(self, sink, dtype):
        self.sink, self.dtype, self.table, self.ends = sink, np.dtype(dtype), [], []
        self.pack = zstandard.ZstdCompressor(level=1)
        self.keys, self.rows, self.held = [], [], 0

    def add(self, key: int | None, ids: np.ndarray) -> None:
        self.keys.append(NO_ID if key is None else key)
        self.rows.append(ids)
        self.held += len(ids)
        if self.held >= FRAME_TOKENS or len(self.keys) >= 1 << 14:
            self.flush()

    def flush(self) -> None:
        if not self.keys:
            return
        head = struct.pack("<II", len(self.keys), self.dtype.itemsize)
        sizes = np.fromiter(map(len, self.rows), "<u4", len(self.rows))
        raw = head + np.array(self.keys, "<i8").tobytes() + sizes.tobytes() + np.concatenate(self.rows).astype(self.dtype).tobytes()
        packed = self.pack.compress(raw)
        self.sink.write(packed)
        self.table.append((len(packed), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
        self.ends += [self.keys[0], self.keys[-1]]
        self.keys, self.rows, self.held = [], [], 0

    def close(self) -> None:
        self.flush()
        held = np.array(self.ends, "<i8").tobytes()
        self.sink.write(struct.pack("<II", DIRECTORY, len(held)) + held)
        body = b"".join(struct.pack("<III", *x) for x in self.table) + struct.pack("<IBI", len(self.table), CHECKSUMS, FOOTER)
        self.sink.write(struct.pack("<II", SKIPPABLE, len(body)) + body)
        self.sink.close()


class FrameReader:
    """Random access to a shard file: only the frames asked for are read and decompressed."""

    def __init__(self, source):
        self.source, size = source, source.size()
        source.seek(size - 9)
        count, flags, magic = struct.unpack("<IBI", source.read(9))
        if magic != FOOTER or flags != CHECKSUMS:
            raise ValueError("no seek table at the end of the file")
        source.seek(size - 9 - 28 * count - 16)
        magic, held = struct.unpack("<II", source.read(8))
        if magic != DIRECTORY or held != 16 * count:
            raise ValueError("no directory before the seek table")
        self.ends = np.frombuffer(source.read(held), "<i8").reshape(count, 2)  # first and last id of each frame
        source.seek(size - 9 - 12 * count)
        table = np.frombuffer(source.read(12 * count), "<u4").reshape(count, 3).astype(np.int64)
        self.packed, self.raw, self.sums = table[:, 0], table[:, 1], table[:, 2]
        self.at = np.concatenate([[0], np.cumsum(self.packed)])

    def frame(self, k: int) -> tuple[np.ndarray, list[np.ndarray]]:
        """Document ids and their token ids in frame k; a damaged frame raises."""
        self.source.seek(int(self.at[k]))
        raw = zstandard.ZstdDecompressor().decompress(self.source.read(int(self.packed[k])), max_output_size=int(self.raw[k]))
        if len(raw) != self.raw[k] or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != self.sums[k]:
            raise ValueError(f"frame {k} fails its checksum")
        n, width = struct.unpack_from("<II", raw)
        keys, sizes = np.frombuffer(raw, "<i8", n, 8), np.frombuffer(raw, "<u4", n, 8 + 8 * n)
        ids = np.frombuffer(raw, f"<u{width}", offset=8 + 12 * n)
        return keys, np.split(ids, np.cumsum(sizes[:-1], dtype=np.int64)) if n else []

    def __len__(self) -> int:
        return len(self.packed)


def _open(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri if "://" in uri or uri.startswith("file:") else f"file://{uri}")


def write_shards(docs: DataFrame, folder: str, tokenizer: str, end_id: int, id_col: str = "doc_id", text_col: str = "text",
                 shards: int | None = None) -> list[tuple[str, int, int]]:
    """Write the shards in ascending id order; returns (file, documents, tokens) per shard, in order.

    Documents are range-partitioned once, as text; every task encodes its sorted rows as they stream by and writes one
    file under a name of its attempt, so a task that is run again never meets a half-written file.  The list has one
    entry per file.
    """
    source = docs.select(F.col(id_col).cast("bigint").alias("row_key"), F.col(text_col).cast("string").alias("body")).select(
        "row_key", "body", F.xxhash64("body").alias("place"), F.monotonically_increasing_id().alias("grain"))
    order = ["row_key", "place", "grain"]  # so that rows of one id, or of none, can be dealt to several shards
    ranged = source.repartitionByRange(shards, *order) if shards else source.repartitionByRange(*order)

    def write(batches):
        writer, coder, first, docs_n, tokens = None, None, None, 0, 0
        for batch in batches:
            keys, texts = batch.column(0).to_pylist(), pc.fill_null(batch.column(1), "").cast(pa.large_binary())
            for at, to in pieces(texts):
                if writer is None:
                    context = TaskContext.get()
                    files, base = _open(folder)
                    files.create_dir(base, recursive=True)
                    name = f"part-{context.partitionId():06d}-{context.taskAttemptId()}.zst"
                    coder = encoder(tokenizer)
                    writer, first = FrameWriter(files.open_output_stream(f"{base}/{name}", compression=None), coder.dtype), context.partitionId()
                for key, ids in zip(keys[at:to], coder.encode(texts.slice(at, to - at).to_pylist(), end_id)):
                    writer.add(key, ids)
                    docs_n, tokens = docs_n + 1, tokens + len(ids)
        if writer is not None:
            writer.close()
            yield pa.record_batch([pa.array([first], pa.int32()), pa.array([name]), pa.array([docs_n], pa.int64()), pa.array([tokens], pa.int64())],
                                  names=["part", "file", "docs", "tokens"])

    done = ranged.sortWithinPartitions(*order).select("row_key", "body").mapInArrow(write, "part int, file string, docs bigint, tokens bigint")
    return [(f"{folder}/{r[1]}", r[2], r[3]) for r in sorted(done.collect())]


def read_shards(spark: SparkSession, files: list[tuple[str, int, int]]) -> DataFrame:
    """(doc_id, start, n_tokens, ids_crc32) of every document, decoded from the files, frame by frame."""
    starts = np.cumsum([0] + [f[2] for f in files])
    rows = [(path, int(starts[i])) for i, (path, _, _) in enumerate(files)]
    parts = spark.createDataFrame(rows, "file string, base bigint").repartition(max(1, len(rows))) if rows else spark.createDataFrame([], "file string, base bigint")

    def read(batches):
        for batch in batches:
            for path, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                files, name = _open(path)
                with files.open_input_file(name) as source:
                    reader = FrameReader(source)
                    for k in range(len(reader)):
                        keys, ids = reader.frame(k)
                        sizes = np.array([len(x) for x in ids], dtype=np.int64)
                        sums = [zlib.crc32(x.astype("<u4").tobytes()) for x in ids]
                        yield pa.record_batch(
                            [pa.array(keys, pa.int64(), mask=keys == NO_ID), pa.array(base + np.cumsum(sizes) - sizes), pa.array(sizes), pa.array(sums, pa.int64())],
                            names=["doc_id", "start", "n_tokens", "ids_crc32"])
                        base += int(sizes.sum())

    return parts.mapInArrow(read, "doc_id bigint, start bigint, n_tokens bigint, ids_crc32 bigint")


def lookup(path: str, wanted: set[int]) -> dict[int, np.ndarray]:
    """Token ids of some documents of one shard; only frames whose id range holds a wanted id are read.

    Of rows that share an id, the first is returned.
    """
    files, name = _open(path)
    found: dict[int, np.ndarray] = {}
    with files.open_input_file(name) as source:
        reader = FrameReader(source)
        by_frame: dict[int, list[int]] = {}
        for key in sorted(wanted):
            k = int(np.searchsorted(reader.ends[:, 1], key))
            if k < len(reader) and reader.ends[k, 0] <= key:
                by_frame.setdefault(k, []).append(key)
        for k, keys in by_frame.items():
            held, ids = reader.frame(k)
            for key in keys:
                at = int(np.searchsorted(held, key))
                if at < len(held) and held[at] == key:
                    found[key] = ids[at]
    return found


def public_tokenizer(name: str = "word_bpe_49k.json") -> str:
    import public_tokenizers

    return public_tokenizers.path(name)


def op8_token_output(spark: SparkSession, sf_dir: str) -> DataFrame:
    docs = spark.read.parquet(f"{sf_dir}/documents.parquet")
    return read_shards(spark, write_shards(docs, scratch(spark, "token-shards"), public_tokenizer(), 2))
