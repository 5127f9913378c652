"""Operator 4: token ids in files, packed by the context-mixing range coder of ``idcoder``.

Writing: documents are range-partitioned by id, so files follow ascending ids; each task sorts its range, encodes
it and cuts it at document ends into groups of about ``GROUP`` ids. A group is one row of the file:
its document table (ids, lengths), the dictionary of its ids, and its blocks, each coded from a
reset model with its own CRC. Reading decodes a group's blocks side by side and checks every CRC.
Where a document starts among all ids follows from prefix sums over the groups' totals.

The files are Parquet (one row per group), so writing is committed by Spark and a lost task is simply
run again, on any file system.

The tokenizer drops white space and never matches across it, so a text is split at ASCII white space
and each distinct piece is encoded once, in a memo of bounded size.

Defined cases: null and empty texts give the end id alone; null ids come first (and are one
document per row); rows that share an id follow each other, by text; texts are used whole; an empty
table writes no group and reads as no rows.
"""

from __future__ import annotations

import os
import re
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession, Window
from pyspark.sql import functions as F

from trailgraph.functions.runtime import scratch_path, shuffle_width
from trailgraph.llm import idcoder
from trailgraph.llm.textarrays import chunks

GROUP, END, MEMO = 3 << 21, 2, 1 << 19
FILE = "part int, seq int, n_ids long, doc_ids binary, nulls binary, lengths binary, dictionary binary, sizes binary, crcs binary, payload binary"
#: What the tokenizer's own split gives on lower-case ASCII.
_PLAIN = re.compile(rb"'s|'t|'re|'ve|'m|'ll|'d|[a-z]+|[0-9]|[^\sa-z0-9]+")


class Encoder:
    """Ids of whole texts as little-endian unsigned 32-bit integers."""

    def __init__(self, path: str):
        os.environ.setdefault("TOKENIZERS_PARALLELISM", "false")  # tasks share the cores already
        from tokenizers import Tokenizer

        self.model = Tokenizer.from_file(path)
        self.model.no_truncation()
        self.model.no_padding()
        self.special = [t.content.encode() for t in self.model.get_added_tokens_decoder().values()]
        probe = "It's 12 o'clock,\n<b>NOW</b> — Straße №5"
        self.splits = [x for p in probe.split() for x in self._ids(p)] == self._ids(probe) and all(len(s.split()) == 1 for s in self.special)
        self.plain = self.splits and all(s.startswith(b"<|") for s in self.special) and all(self._joined(p) == self._ids(p.decode()) for p in (b"it's12,ok", b"don't...stop", b"<a>'ll1've", b"x_y-z"))
        single = [chr(c) for c in range(33, 127) if not 65 <= c <= 90]  # the model alone has to know each as the whole tokenizer does
        self.direct = self.plain and all(self._alone(p) == self._ids(p) for p in [*single, "'ll", "...!?", "#*$%&|<>", "unforeseeably", "qzxjkvw"])
        self.memo: dict[bytes, bytes] = {}
        self.parts: dict[bytes, bytes] = {}

    def _ids(self, text: str) -> list[int]:
        return self.model.encode(text, add_special_tokens=False).ids

    def _alone(self, part: str) -> list[int]:
        """Ids of a part of printable lower-case ASCII by the tokenizer's model, without its other steps."""
        return [t.id for t in self.model.model.tokenize(part)]

    def _joined(self, piece: bytes) -> list[int]:
        return [i for p in _PLAIN.findall(piece) for i in self._ids(p.decode())]

    def encode(self, text: bytes) -> bytes:
        if not self.splits:
            return np.array(self._ids(text.decode("utf-8", "replace")), "<u4").tobytes()
        pieces = text.split()
        got = list(map(self.memo.get, pieces))
        if None in got:
            self._learn([p for p, g in zip(pieces, got) if g is None])
            got = [self.memo[p] if g is None else g for p, g in zip(pieces, got)]
        return b"".join(got)

    def _batch(self, pieces: list[bytes]) -> list[bytes]:
        got = self.model.encode_batch_fast([p.decode("utf-8", "replace") for p in pieces], add_special_tokens=False)
        return [np.array(e.ids, "<u4").tobytes() for e in got]

    def _learn(self, pieces: list[bytes]) -> None:
        """Ids of new pieces. Plain ASCII ones are put together from their parts, so that few go to the library."""
        new = list(dict.fromkeys(pieces))
        if len(self.memo) + len(new) > MEMO:
            self.memo = {}  # begun anew; the caller has what it found
        if len(self.parts) > MEMO:
            self.parts = {}
        hard, simple, missing = [], [], {}
        for p in new:
            if self.plain and p.isascii() and b"<|" not in p:
                parts = _PLAIN.findall(p.lower())
                simple.append((p, parts))
                for x in parts:
                    if x not in self.parts:
                        missing[x] = None
            else:
                hard.append(p)
        known, whole = self.parts, []
        if self.direct:
            tokenize = self.model.model.tokenize
            for x in missing:
                if (part := x.decode()).isprintable():
                    known[x] = np.array([t.id for t in tokenize(part)], "<u4").tobytes()
                else:
                    whole.append(x)
        else:
            whole = list(missing)
        ids = self._batch([*whole, *hard])
        known.update(zip(whole, ids))
        self.memo.update(zip(hard, ids[len(whole) :]))
        for p, parts in simple:
            self.memo[p] = b"".join([known[x] for x in parts])


_encoders: dict[str, Encoder] = {}


def encoder(path: str) -> Encoder:
    if path not in _encoders:
        _encoders[path] = Encoder(path)
    return _encoders[path]


def _group(part: int, seq: int, docs: list, streams: list[bytes]) -> tuple:
    ids = np.frombuffer(b"".join(streams), "<u4")
    lengths = np.array([len(s) // 4 for s in streams], np.uint32)
    known, blocks, crcs = idcoder.encode(ids)
    sizes = np.array([len(b) // 4 for b in blocks], np.uint32)
    names = np.array([0 if d is None else d for d in docs], np.int64)
    nulls = np.array([d is None for d in docs], np.uint8)
    return part, seq, len(ids), names.tobytes(), nulls.tobytes(), lengths.tobytes(), known.astype(np.uint32).tobytes(), sizes.tobytes(), crcs.tobytes(), b"".join(blocks)


_ARROW = [("part", pa.int32()), ("seq", pa.int32()), ("n_ids", pa.int64()), *[(k, pa.binary()) for k in ("doc_ids", "nulls", "lengths", "dictionary", "sizes", "crcs", "payload")]]


def write(docs: DataFrame, path: str, tokenizer: str, id_col: str = "doc_id", text_col: str = "text", end_id: int | None = END, group: int = GROUP) -> None:
    """Write the ids of every row of ``docs`` under ``path``, in ascending order of ``id_col``."""
    width = shuffle_width(docs, 16 << 20, 1.75)  # a partition is about one group
    rows = docs.select(F.col(f"`{id_col}`").cast("long").alias("doc_id"), F.col(f"`{text_col}`").cast("string").alias("text"))
    rows = rows.repartitionByRange(width, "doc_id", F.xxhash64("text")).sortWithinPartitions("doc_id", F.xxhash64("text")).withColumn("part", F.spark_partition_id())
    end = b"" if end_id is None else np.array([end_id], "<u4").tobytes()

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        enc, seq, size, part = encoder(tokenizer), 0, 0, 0
        names: list = []
        streams: list[bytes] = []
        distinct: set = set()

        def close() -> pa.RecordBatch:
            row = _group(part, seq, names, streams)
            return pa.RecordBatch.from_arrays([pa.array([x], t) for x, (_, t) in zip(row, _ARROW)], names=[k for k, _ in _ARROW])

        for b in batches:
            part = b.column(2)[0].as_py() if b.num_rows else part
            for c in chunks(b.column(1)):
                ids = b.column(0).slice(c.first, c.n).to_pylist()
                for i in range(c.n):
                    stream = enc.encode(c.text(i)) + end
                    names.append(ids[i])
                    streams.append(stream)
                    size += len(stream) // 4
                    if size >= group:
                        yield close()
                        names, streams, size, seq = [], [], 0, seq + 1
        if names:
            yield close()

    rows.mapInArrow(run, FILE).write.parquet(path)


def read(spark: SparkSession, path: str, with_ids: bool = False) -> DataFrame:
    """doc_id, start, n_tokens, ids_crc32 (and ids binary) of every document in the files under ``path``."""
    files = spark.read.schema(FILE).parquet(path)
    by_part = files.groupBy("part").agg(F.sum("n_ids").alias("n"))
    before = by_part.select(F.col("part").alias("p"), (F.sum("n").over(Window.orderBy("part")) - F.col("n")).alias("before"))
    within = files.select(F.col("part").alias("wp"), F.col("seq").alias("ws"), (F.sum("n_ids").over(Window.partitionBy("part").orderBy("seq")) - F.col("n_ids")).alias("inside"))
    starts = within.join(before, F.col("wp") == F.col("p")).select("wp", "ws", (F.col("before") + F.col("inside")).alias("start"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            for r in range(b.num_rows):
                part, seq, n, names, nulls, lengths, known, sizes, crcs, payload = (b.column(k)[r].as_py() for k in range(10))
                lengths, sizes = np.frombuffer(lengths, np.uint32), np.frombuffer(sizes, np.uint32).astype(np.int64)
                at = np.concatenate([[0], np.cumsum(sizes)]) * 4
                ids = idcoder.decode(np.frombuffer(known, np.uint32), [payload[i:j] for i, j in zip(at[:-1], at[1:])], n, np.frombuffer(crcs, np.uint32))
                to = np.cumsum(lengths.astype(np.int64))
                raw = ids.astype("<u4").tobytes()
                parts = [raw[4 * (e - k) : 4 * e] for e, k in zip(to.tolist(), lengths.tolist())]
                yield pa.RecordBatch.from_arrays(
                    [
                        pa.array(np.full(len(to), part, np.int32)), pa.array(np.full(len(to), seq, np.int32)),
                        pa.array(np.frombuffer(names, np.int64), mask=np.frombuffer(nulls, np.uint8).astype(bool)),
                        pa.array(to - lengths), pa.array(lengths.astype(np.int64)), pa.array([zlib.crc32(x) for x in parts], pa.int64()), pa.array(parts if with_ids else [None] * len(parts), pa.binary()),
                    ],
                    names=["part", "seq", "doc_id", "at", "n_tokens", "ids_crc32", "ids"],
                )

    docs = files.mapInArrow(run, "part int, seq int, doc_id long, at long, n_tokens long, ids_crc32 long, ids binary")
    x = docs.join(starts, (F.col("part") == F.col("wp")) & (F.col("seq") == F.col("ws")))
    out = x.select("doc_id", (F.col("start") + F.col("at")).alias("start"), "n_tokens", "ids_crc32", "ids")
    return out if with_ids else out.drop("ids")


def roundtrip(docs: DataFrame, tokenizer: str, **kw) -> DataFrame:
    """Write to the shared folder and read back."""
    path = scratch_path(docs.sparkSession, "token-ids")
    write(docs, path, tokenizer, **kw)
    return read(docs.sparkSession, path)
