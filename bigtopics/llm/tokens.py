"""Token ids of whole texts, and their binary files.

Encoding.  A text is cut at ASCII white space; the pieces are encoded once per
worker and kept in a bounded cache.  With the given tokenizer no token, no
normalisation and no special token reaches over ASCII white space, so the ids
of the pieces in order are the ids of the text (tested against whole-text
encoding).  Pieces of Latin letters go straight to the tokenizer's BPE model;
any other piece goes through the whole tokenizer.

File format.  One Zstandard frame per document (long ones: several), each
independent; then a skippable frame with the index of documents; last a seek
table in the public Zstandard seekable format: compressed size, decompressed
size and the low 32 bits of XXH64 of each frame, and a footer.  A reader opens
the table and decompresses the frames of the requested documents only.

Defined cases: a null text is empty and holds the end id alone; null ids come
first; repeated ids are documents of their own; an empty table writes no file.
"""

from __future__ import annotations

import contextlib
import os
import re
import struct
import zlib
from array import array
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import fresh_path, give_back, text_of

END_ID = 2
_PLAIN = re.compile("[!-~¡-įı-ſ]*")
_SPLIT = r"'s|'t|'re|'ve|'m|'ll|'d|[\p{L}]+|[\p{N}]|[^\s\p{L}\p{N}]+"  # fixed value: the tokenizer's own split
_MARKS = "!\"#$%&()*+,-./:;<=>?@[\\]^_`{|}~'"
_BYTES_AT_ONCE = 8 << 20


def _byte_letters() -> dict[int, str]:
    """The byte-level alphabet: printable Latin-1 bytes stand for themselves, the others follow from 256 on."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    rest = [b for b in range(256) if b not in plain]
    return {b: chr(b) for b in plain} | {b: chr(256 + i) for i, b in enumerate(rest)}


class Encoder:
    """Encodes columns of whole texts; keeps the ids of about ``limit`` pieces, those met again before others."""

    def __init__(self, path: str, limit: int = 400_000):
        import regex
        from tokenizers import Tokenizer

        self.whole = Tokenizer.from_file(path)
        self.model, self.limit = self.whole.model, limit
        self.letters = _byte_letters()
        self.find = regex.compile(_SPLIT).findall
        self.known, self.parts = {"": 0}, {}
        self.ids, self.begin, self.length, self.again = array("I"), array("q", [0]), array("q", [0]), bytearray(1)

    def shrink(self) -> None:
        """Drops pieces that were met in one slice only; all, if that is not enough."""
        keep = {s: k for s, k in self.known.items() if self.again[k] or not s}
        if len(keep) > self.limit // 2:
            keep = {"": 0}
        at = np.fromiter(keep.values(), np.int64, len(keep))
        ids, length = self._gather(at), np.frombuffer(self.length, np.int64)[at]
        self.known, self.parts = {s: k for k, s in enumerate(keep)}, {}
        self.ids, self.length = array("I", ids.tobytes()), array("q", length.tobytes())
        self.begin, self.again = array("q", (np.cumsum(length) - length).tobytes()), bytearray(len(keep))

    def _gather(self, at: np.ndarray) -> np.ndarray:
        """Ids of the known pieces at these places, one after the other."""
        begin, length = np.frombuffer(self.begin, np.int64)[at], np.frombuffer(self.length, np.int64)[at]
        flat = np.arange(int(length.sum())) + np.repeat(begin - (np.cumsum(length) - length), length)
        return np.frombuffer(self.ids, np.uint32)[flat] if len(flat) else np.empty(0, np.uint32)

    def part(self, s: str) -> array:
        span = self.parts.get(s)
        if span is None:
            letters = s if s.isascii() else s.encode().decode("latin-1").translate(self.letters)
            got = array("I", [t.id for t in self.model.tokenize(letters)])
            self.parts[s] = len(self.ids) << 24 | len(got)
            self.ids.extend(got)
            return got
        a = span >> 24
        return self.ids[a : a + (span & 0xFFFFFF)]

    def add(self, s: str) -> int:
        """Encodes a piece and gives its place."""
        low = s.lower()
        if "<|" in s or len(s) > 1 << 20 or not _PLAIN.fullmatch(s):
            got = array("I", self.whole.encode(s, add_special_tokens=False).ids)
        elif low.isalpha():
            n = len(self.part(low))
            self.begin.append(self.parts[low] >> 24)
            self.length.append(n)
            self.again.append(0)
            return len(self.begin) - 1
        elif (head := low.rstrip(_MARKS)).isalpha():  # a word and marks after it: two parts
            got = self.part(head) + self.part(low[len(head) :])
        else:
            got = array("I")
            for p in self.find(low):
                got.extend(self.part(p))
        self.begin.append(len(self.ids))
        self.length.append(len(got))
        self.again.append(0)
        self.ids.extend(got)
        return len(self.begin) - 1

    def encode(self, texts: pa.Array) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, END_ID after each, and the number of ids of each."""
        if len(self.known) > self.limit:
            self.shrink()
        cut = pc.ascii_split_whitespace(texts)
        many = np.asarray(pc.list_value_length(cut)).astype(np.int64)
        pieces = cut.flatten().dictionary_encode()
        del cut
        unique, where = pieces.dictionary.to_pylist(), np.asarray(pieces.indices)
        at = np.empty(len(unique), np.int64)
        known, again = self.known, self.again
        for j, s in enumerate(unique):
            k = known.get(s)
            if k is None:
                k = known[s] = self.add(s)
            else:
                again[k] = 1
            at[j] = k
        del unique, pieces
        each = at[where]
        doc_end = np.concatenate([[0], np.cumsum(np.frombuffer(self.length, np.int64)[each])])[np.cumsum(many)]
        return np.insert(self._gather(each), doc_end, END_ID), np.diff(doc_end, prepend=0) + 1


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    """The worker's encoder for a vocabulary file, kept between tasks."""
    if path not in _encoders:
        _encoders.clear()
        _encoders[path] = Encoder(path)
    return _encoders[path]


def encoded(batches: Iterator[pa.RecordBatch], path: str, text: str) -> Iterator[tuple[pa.RecordBatch, np.ndarray, np.ndarray]]:
    """(slice of a batch, its ids, number of ids of each row), in slices of bounded size."""
    enc = encoder(path)
    for batch in batches:
        sizes = np.asarray(pc.fill_null(pc.binary_length(batch.column(text)), 0)).astype(np.int64)
        group = np.cumsum(sizes) // _BYTES_AT_ONCE
        edges = [0, *(np.flatnonzero(np.diff(group)) + 1).tolist(), len(sizes)]
        for a, b in zip(edges, edges[1:], strict=False):
            if b > a:
                part = batch.slice(a, b - a)
                yield part, *enc.encode(pc.fill_null(part.column(text), ""))
    give_back()


# --- files ------------------------------------------------------------------------------------------

# Fixed values of the Zstandard seekable format.
_SEEK_MAGIC, _FOOT_MAGIC, _INDEX_MAGIC = 0x184D2A5E, 0x8F92EAB1, 0x184D2A50
_CHECKSUMS = 0x80


def _filesystem(uri: str):
    from pyarrow import fs

    return fs.FileSystem.from_uri(uri)


class FrameWriter:
    """Writes documents of token ids to one file."""

    def __init__(self, sink, level: int = 1, frame_ids: int = 1 << 16):
        import zstandard

        self.sink, self.frame_ids = sink, frame_ids
        self.squeeze = zstandard.ZstdCompressor(level=level).compress
        self.table, self.docs = [], []

    def add(self, doc_id: int | None, ids: np.ndarray) -> None:
        import xxhash

        for a in range(0, len(ids), self.frame_ids):
            raw = ids[a : a + self.frame_ids].astype("<u4").tobytes()
            frame = self.squeeze(raw)
            self.sink.write(frame)
            self.table.append((len(frame), len(raw), xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF))
        self.docs.append((doc_id or 0, doc_id is None, -(-len(ids) // self.frame_ids), len(ids)))

    def close(self) -> None:
        ids, null, frames, length = (np.array(x) for x in zip(*self.docs, strict=True)) if self.docs else [np.empty(0)] * 4
        index = struct.pack("<Q", len(self.docs)) + ids.astype("<i8").tobytes() + frames.astype("<u4").tobytes() + length.astype("<u8").tobytes() + null.astype("u1").tobytes()
        self.sink.write(struct.pack("<II", _INDEX_MAGIC, len(index)) + index)
        table = np.array([*self.table, (len(index) + 8, 0, 0)], "<u4").tobytes()
        self.sink.write(struct.pack("<II", _SEEK_MAGIC, len(table) + 9) + table + struct.pack("<IBI", len(self.table) + 1, _CHECKSUMS, _FOOT_MAGIC))


class FrameReader:
    """Reads chosen documents of one file."""

    def __init__(self, source):
        self.source = source
        size = source.size()
        n, how, magic = struct.unpack("<IBI", source.read_at(9, size - 9))
        if magic != _FOOT_MAGIC or not how & _CHECKSUMS:
            raise ValueError("no seek table with checksums at the end of the file")
        self.table = np.frombuffer(source.read_at(12 * n, size - 9 - 12 * n), "<u4").reshape(n, 3).astype(np.int64)
        self.at = np.concatenate([[0], np.cumsum(self.table[:, 0])])
        raw = source.read_at(int(self.table[-1, 0]), int(self.at[-2]))
        (docs,) = struct.unpack_from("<Q", raw, 8)
        self.ids = np.frombuffer(raw, "<i8", docs, 16)
        frames = np.frombuffer(raw, "<u4", docs, 16 + 8 * docs).astype(np.int64)
        self.length = np.frombuffer(raw, "<u8", docs, 16 + 12 * docs).astype(np.int64)
        self.null = np.frombuffer(raw, "u1", docs, 16 + 20 * docs)
        self.first = np.concatenate([[0], np.cumsum(frames)])

    def __len__(self) -> int:
        return len(self.ids)

    def read(self, k: int) -> np.ndarray:
        """The ids of the k-th document; no other frame is read."""
        import xxhash
        import zstandard

        out, a, b = [], int(self.first[k]), int(self.first[k + 1])
        data = self.source.read_at(int(self.at[b] - self.at[a]), int(self.at[a]))
        for f in range(a, b):
            at = int(self.at[f] - self.at[a])
            raw = zstandard.decompress(data[at : at + int(self.table[f, 0])])
            if len(raw) != self.table[f, 1] or xxhash.xxh64_intdigest(raw) & 0xFFFFFFFF != self.table[f, 2]:
                raise ValueError(f"frame {f} does not match its checksum")
            out.append(np.frombuffer(raw, "<u4"))
        return np.concatenate(out) if out else np.empty(0, "<u4")

    def find(self, doc_id: int | None) -> list[int]:
        """Places of the documents with this id."""
        return np.flatnonzero((self.null == 1) if doc_id is None else (self.ids == doc_id) & (self.null == 0)).tolist()


def write_tokens(docs: DataFrame, folder: str, tokenizer: str, *, id_col: str = "doc_id", text_col: str = "text") -> list[tuple[str, int, int]]:
    """Writes docs in ascending order of id, one file per range of ids; returns (file, documents, ids) of each, in order.

    What comes to the driver is one row per file.  A task writes under a name of
    its attempt and renames it when whole, so retries and lost executors leave no half files.
    """
    ordered = docs.select(F.col(id_col).cast("long").alias("id"), text_of(text_col).alias("text")).withColumn("tie", F.xxhash64("text"))
    ordered = ordered.repartitionByRange(F.asc_nulls_first("id"), "tie").sortWithinPartitions(F.asc_nulls_first("id"), "tie").select("id", "text")
    schema = pa.schema([("part", pa.int64()), ("file", pa.string()), ("docs", pa.int64()), ("ids", pa.int64())])

    def write(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        context, fs, root = TaskContext.get(), *_filesystem(folder)
        part, total, out, sink = context.partitionId(), 0, None, None
        name, draft = f"{root}/tokens-{part:06d}.zst", f"{root}/.draft-{part:06d}-{context.taskAttemptId()}"
        for batch, ids, many in encoded(batches, tokenizer, "text"):
            if out is None:
                fs.create_dir(root, recursive=True)
                sink = fs.open_output_stream(draft)
                out = FrameWriter(sink)
            for doc_id, row in zip(batch.column("id").to_pylist(), np.split(ids, np.cumsum(many)[:-1]), strict=True):
                out.add(doc_id, row)
            total += len(ids)
        if out is not None:
            out.close()
            sink.close()
            fs.move(draft, name)
            yield pa.RecordBatch.from_arrays([[part], [f"{folder}/{os.path.basename(name)}"], [len(out.docs)], [total]], schema=schema)

    written = ordered.mapInArrow(write, "part long, file string, docs long, ids long").collect()
    return [(r.file, r.docs, r.ids) for r in sorted(written, key=lambda r: r.part)]


def read_tokens(spark: SparkSession, files: list[tuple[str, int, int]]) -> DataFrame:
    """One row per document of the files: doc_id, start (ids of all documents before it), ids (array<int>) crc and count."""
    before = np.concatenate([[0], np.cumsum([n for _, _, n in files])]).tolist()
    todo = spark.createDataFrame([(f, b) for (f, _, _), b in zip(files, before, strict=False)] or [], "file string, base long")
    schema = pa.schema([("doc_id", pa.int64()), ("start", pa.int64()), ("n_tokens", pa.int64()), ("ids_crc32", pa.int64())])

    def read(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for file, base in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist(), strict=True):
                fs, path = _filesystem(file)
                with contextlib.closing(fs.open_input_file(path)) as source:
                    got = FrameReader(source)
                    for a in range(0, len(got), 10_000):
                        rows = range(a, min(a + 10_000, len(got)))
                        ids = [got.read(k) for k in rows]
                        n = np.array([len(x) for x in ids], np.int64)
                        start = base + np.cumsum(n) - n
                        base += int(n.sum())
                        doc_ids = [None if got.null[k] else int(got.ids[k]) for k in rows]
                        yield pa.RecordBatch.from_arrays([pa.array(doc_ids, pa.int64()), pa.array(start), pa.array(n), pa.array([zlib.crc32(x.tobytes()) for x in ids], pa.int64())], schema=schema)

    return todo.repartition(max(1, len(files))).mapInArrow(read, "doc_id long, start long, n_tokens long, ids_crc32 long")


def token_files(docs: DataFrame, tokenizer: str, *, folder: str | None = None, **columns) -> DataFrame:
    """Writes docs to token files, reads them back and digests what was read, a row per document."""
    spark = docs.sparkSession
    return read_tokens(spark, write_tokens(docs, folder or fresh_path(spark, "tokens"), tokenizer, **columns))
