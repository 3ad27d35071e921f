"""Best-fit packing of tokenised documents into sequences of a fixed length.

The plan is made over counts: pieces are counted by length, and best-fit decreasing runs over that
histogram, many equal bins at a time, on the driver (at most as many entries as a sequence has
tokens). The result is, for each length, which ranks go to which sequences at which offset. Pieces
then take their places by their rank within their length. Ranks come from two levels: lengths with
many pieces are dealt over salts, the salts' counts give where each begins, and a window numbers the
few pieces of one length and salt.

Defined cases: a null text counts as empty and has the closing id alone; a longer document is cut into
full pieces after a first one that takes the rest; repeated rows are packed each; an empty table
gives no rows; other columns of the documents are not carried on.
"""

from __future__ import annotations

import json
import math
import zlib
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import tiktoken
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F
from pyspark.sql import Window as W

from . import textbuf, tokenfsm
from .common import cut, read
from .grouped import caches, enter

CAPACITY, CLOSING = 2048, 0


class Encoder:
    """Ids of the byte-level BPE tokenizer in a file: pieces by the compiled splitter, each distinct piece merged once."""

    def __init__(self, path: str) -> None:
        with open(path, encoding="utf-8") as f:
            data = json.load(f)
        vocabulary, byte = data["model"]["vocab"], tokenfsm.byte_letters()
        self.added = {t["content"]: t["id"] for t in data.get("added_tokens", [])}
        back = {c: b for b, c in enumerate(byte)}
        merges = [m.split(" ") if isinstance(m, str) else m for m in data["model"]["merges"]]
        names = [*byte, *(a + b for a, b in merges)]
        self.ids = np.array([vocabulary[s] for s in names], np.int32)
        ranks = {bytes(back[c] for c in s): i for i, s in enumerate(names)}
        self.bpe = tiktoken.Encoding("pieces", pat_str=r"[^\x00]+|\x00", mergeable_ranks=ranks, special_tokens={})
        self.start, self.size, self.pool, self.used = np.zeros(1 << 16, np.int64), np.zeros(1 << 16, np.int32), np.zeros(1 << 18, np.int32), 0
        self.n = 0
        self._add([np.array([CLOSING], np.int32)])  # entry 0 closes a document
        self.splitter = tokenfsm.Splitter(path, self._resolve)

    def _add(self, many: list[np.ndarray]) -> np.ndarray:
        size = np.array([len(x) for x in many], np.int32)
        flat = np.concatenate(many) if many else np.empty(0, np.int32)
        while self.n + len(many) > len(self.start):
            self.start, self.size = np.resize(self.start, 2 * len(self.start)), np.resize(self.size, 2 * len(self.size))
        while self.used + len(flat) > len(self.pool):
            self.pool = np.resize(self.pool, 2 * len(self.pool))
        at = slice(self.n, self.n + len(many))
        self.start[at] = self.used + np.cumsum(size, dtype=np.int64) - size
        self.size[at] = size
        self.pool[self.used : self.used + len(flat)] = flat
        self.used, self.n = self.used + len(flat), self.n + len(many)
        return np.arange(at.start, at.stop, dtype=np.int32)

    def _resolve(self, words: list[str]) -> np.ndarray:
        """Entries of new distinct pieces: all are merged in one call, with a zero character between them."""
        odd = [i for i, w in enumerate(words) if "\0" in w or w in self.added]
        plain = list(words)
        for i in odd:
            plain[i] = "a"
        ranks = np.array(self.bpe.encode_ordinary("\0".join(plain)), np.int32)
        zero = int(self.bpe.encode_single_token(b"\0"))
        many = np.split(ranks, np.flatnonzero(ranks == zero)) if words else []
        many = [self.ids[x[1:] if k else x] for k, x in enumerate(many)]
        for i in odd:
            many[i] = np.array([self.added[words[i]]], np.int32) if words[i] in self.added else self.ids[np.array(self.bpe._encode_single_piece(words[i].encode()), np.int64)]
        return self._add(many)

    def encode(self, raw: np.ndarray, at: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Ids of all texts, each text followed by the closing id if it ends here, and the offsets of the texts."""
        entries, first = self.splitter.lookup(raw, at)
        entries = np.insert(entries, first[1:], 0)
        ends = first[1:] + np.arange(1, len(first))
        size = self.size[entries].astype(np.int64)
        total = np.concatenate(([0], np.cumsum(size)))
        ids = self.pool[np.repeat(self.start[entries] - total[:-1], size) + np.arange(total[-1])]
        return ids, np.concatenate(([0], total[ends]))


_encoders: dict[str, Encoder] = {}
caches("packing", _encoders.clear)


def encode(column: pa.Array, path: str) -> Iterator[np.ndarray]:
    """Ids of each text of a column with the closing id."""
    enter("packing")
    whole, at, _ = textbuf.utf8(column)
    every, row = tokenfsm.cut_long(whole, at)
    part: list[np.ndarray] = []
    for i, j in textbuf.groups(every):
        if path not in _encoders or _encoders[path].splitter.table.n > tokenfsm.KEEP:
            _encoders[path] = Encoder(path)
        ids, ends = _encoders[path].encode(whole[every[i] : every[j]], every[i : j + 1] - every[i])
        for k in range(j - i):
            part.append(ids[ends[k] : ends[k + 1]])
            if i + k + 2 == len(row) or row[i + k + 1] != row[i + k]:
                yield part[0] if len(part) == 1 else np.concatenate([*(x[:-1] for x in part[:-1]), part[-1]])
                part = []


def cut_pieces(docs: DataFrame, path: str, capacity: int = CAPACITY, text: str = "text", key: str = "doc_id", with_ids: bool = False) -> DataFrame:
    """Pieces of at most ``capacity`` ids: key, piece, start, length, ids_crc32 and on request the ids."""

    def pieces(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            rows, held = [], []
            for i, ids in enumerate(encode(b.column(1), path)):
                edges = [0, *range(len(ids) % capacity or capacity, len(ids) + 1, capacity)] if len(ids) > capacity else [0, len(ids)]
                for k, (s, e) in enumerate(zip(edges, edges[1:], strict=False)):
                    rows.append((i, k, s, e - s, zlib.crc32(ids[s:e].astype("<u4").tobytes())))
                    if with_ids:
                        held.append(ids[s:e])
            i, k, s, n, c = np.array(rows, np.int64).reshape(-1, 5).T
            columns = [b.column(0).take(pa.array(i)), pa.array(k, pa.int32()), pa.array(s), pa.array(n), pa.array(c)]
            if with_ids:
                columns.append(pa.ListArray.from_arrays(pa.array(np.concatenate(([0], np.cumsum(n))), pa.int32()), pa.array(np.concatenate(held) if held else np.empty(0, np.int32), pa.int32())))
            yield pa.RecordBatch.from_arrays(columns, ["doc_id", "piece", "start", "length", "ids_crc32", "ids"][: len(columns)])

    kind = docs.schema[key].dataType.simpleString()
    return docs.select(key, text).mapInArrow(pieces, f"doc_id {kind}, piece int, start long, length long, ids_crc32 long" + ", ids array<int>" * with_ids)


def plan(histogram: dict[int, int], capacity: int = CAPACITY) -> np.ndarray:
    """Best fit over counts: rows (length, first rank, sequence, pieces of this length in a sequence, offset in it).

    From its first rank on, the k-th piece goes to sequence ``sequence + k // per``, at ``offset + k % per * length``.
    """
    room: dict[int, list[tuple[int, int]]] = {}  # room left -> ranges (first sequence, number)
    out, sequences = [], 0
    for length in sorted(histogram, reverse=True):
        left, rank = histogram[length], 0
        for space in sorted(r for r in room if r >= length):
            per = space // length
            while left and room.get(space):
                first, n = room[space].pop()
                whole = min(n, left // per)
                take, used = (whole, per) if whole else (1, left)
                out.append((length, rank, first, used, capacity - space))
                rank, left = rank + take * used, left - take * used
                room.setdefault(space - used * length, []).append((first, take))
                if take < n:
                    room[space].append((first + take, n - take))
        if left:
            per = capacity // length
            whole, rest = divmod(left, per)
            if whole:
                out.append((length, rank, sequences, per, 0))
                room.setdefault(capacity - per * length, []).append((sequences, whole))
            if rest:
                out.append((length, rank + whole * per, sequences + whole, rest, 0))
                room.setdefault(capacity - rest * length, []).append((sequences + whole, 1))
            sequences += whole + bool(rest)
        room = {r: v for r, v in room.items() if v and r}
    return np.array(sorted(out), np.int64).reshape(-1, 5)


def pack(pieces: DataFrame, capacity: int = CAPACITY) -> DataFrame:
    """``pieces`` (kept: it is read more than once) with sequence_id and offset."""
    spark = pieces.sparkSession
    histogram = {r[0]: r[1] for r in pieces.groupBy("length").count().collect()}  # at most ``capacity`` rows
    share = max(50, sum(histogram.values()) // 2000)
    salts = spark.createDataFrame([(n, max(1, math.ceil(c / share))) for n, c in histogram.items()], "length long, salts int")
    salted = pieces.join(F.broadcast(salts), "length").withColumn("salt", F.pmod(F.xxhash64("doc_id", "piece"), F.col("salts")).cast("long")).drop("salts")
    groups = salted.groupBy("length", "salt").count().toPandas().sort_values(["length", "salt"])  # at most capacity + 2000 rows
    before = groups.groupby("length")["count"].cumsum() - groups["count"]
    keys, base = (groups["length"] * (1 << 32) + groups["salt"]).to_numpy(np.int64), before.to_numpy(np.int64)
    slots = plan(histogram, capacity)
    shared = spark.sparkContext.broadcast((keys, base, slots[:, 0] * (1 << 40) + slots[:, 1], slots))

    def placed(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        keys, base, order, slots = shared.value
        for b in batches:
            length, salt, number = (b.column(c).to_numpy() for c in ("length", "salt", "_n"))
            rank = base[np.searchsorted(keys, length * (1 << 32) + salt)] + number - 1
            s = slots[np.searchsorted(order, length * (1 << 40) + rank, "right") - 1]
            k = rank - s[:, 1]
            out = [b.column(c) for c in names]
            yield pa.RecordBatch.from_arrays([*out, pa.array(s[:, 2] + k // s[:, 3]), pa.array(s[:, 4] + k % s[:, 3] * length)], [*names, "sequence_id", "offset"])

    names = pieces.columns
    numbered = salted.withColumn("_n", F.row_number().over(W.partitionBy("length", "salt").orderBy("doc_id", "piece", "ids_crc32")).cast("long"))
    schema = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in pieces.schema)
    return numbered.mapInArrow(placed, f"{schema}, sequence_id long, offset long")


def pack_documents(docs: DataFrame, path: str, capacity: int = CAPACITY) -> DataFrame:
    return pack(cut(cut_pieces(docs, path, capacity)), capacity).select("doc_id", "piece", "start", "length", "ids_crc32", "sequence_id", "offset")


def op4_packing(spark: SparkSession, sf_dir: str) -> DataFrame:
    return pack_documents(read(spark, sf_dir, "documents"), public_tokenizers.path("byte_bpe_50k.json"))
