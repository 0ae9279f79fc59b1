"""Packing by shortest-pack-first over the length histogram.

Documents become token ids plus one end id, are cut into pieces of at most `size` ids, and only the histogram of piece lengths (at most
`size` numbers) reaches the driver. There lengths are placed longest first, each into the open packs with the most room,
as counts of packing patterns. Patterns turn into runs (length, ranks, first sequence, offset), joined back to pieces by their rank among pieces of that length.

Null texts count as empty (one end id); repeated rows are packed apart; an empty table packs to nothing; extra columns are ignored.
Memory per task is one Arrow batch and a bounded cache of word pieces.
"""

from __future__ import annotations

import base64
import re
import zlib
from array import array
from collections import defaultdict

import pyarrow as pa
from pyspark.sql import DataFrame, Window
from pyspark.sql import functions as F

from .common import stored

SIZE, END_ID = 1024, 0
SPECIAL, SPECIAL_ID = "<|endoftext|>", 50256
PIECES = "doc_id long, start long, length long, ids_crc32 long, doc_tokens long"
_loaded: dict[str, _Encoder] = {}


class _Encoder(dict):
    """Maps a word with its leading space to its ids as little-endian unsigned 32-bit bytes; forgets all at a bounded size.

    Byte-level BPE first splits a text by a pattern that always splits before a space that stands between two other characters, so words
    are encoded once each. A text with a space between two other white-space characters is encoded whole.
    """

    room = 400_000
    odd = re.compile(r"\s \s")

    def __init__(self, path: str):
        import public_tokenizers
        import tiktoken

        with open(path, "rb") as lines:
            ranks = {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, lines)}
        self.whole = tiktoken.Encoding("byte_bpe", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
        self.single = self.whole._core_bpe.encode_single_piece

    def raw(self, text: str) -> bytes:
        ids = array("I", self.whole.encode_ordinary(text))
        return ids.tobytes()

    def __missing__(self, word: str) -> bytes:
        if len(self) > self.room:
            self.clear()
        body = word[1:] if word[:1] == " " else word
        if body.isalpha():
            made = array("I", self.single(word.encode())).tobytes()
        elif body[-1:] in ".," and body[:-1].isalpha():
            made = self[word[:-1]] + self[word[-1]] if len(word) > 1 else self.raw(word)
        else:
            made = self.raw(word)
        self[word] = made
        return made

    def ids(self, text: str) -> bytes:
        parts = []
        for k, part in enumerate(text.split(SPECIAL)):
            if k:
                parts.append(array("I", [SPECIAL_ID]).tobytes())
            if "\x00" in part or self.odd.search(part):
                parts.append(self.raw(part))
            elif part:
                parts.append(b"".join(map(self.__getitem__, part.replace(" ", "\x00 ").split("\x00"))) if part[0] != " " else b"".join(map(self.__getitem__, part.replace(" ", "\x00 ").split("\x00")[1:])))
        return b"".join(parts)


def encoder(path: str) -> _Encoder:
    if path not in _loaded:
        _loaded[path] = _Encoder(path)
    return _loaded[path]


def default_vocabulary() -> str:
    """The same vocabulary as byte_bpe_50k.json, as ranks; tests hold the ids of both equal."""
    import public_tokenizers

    return public_tokenizers.path("byte_bpe_50k.tiktoken")


def token_pieces(docs: DataFrame, vocabulary: str, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece; with_ids adds the ids themselves as `ids` (bytes)."""
    schema = PIECES + (", ids binary" if with_ids else "")

    def run(batches):
        encode, end = encoder(vocabulary).ids, array("I", [END_ID]).tobytes()
        for batch in batches:
            rows = []
            for doc_id, text in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = encode(text or "") + end
                total = len(ids) // 4
                for start in range(0, total, size):
                    part = ids[start * 4 : (start + size) * 4]
                    rows.append((doc_id, start, len(part) // 4, zlib.crc32(part), total, part)[: 6 if with_ids else 5])
            columns = zip(*rows) if rows else [()] * (6 if with_ids else 5)
            types = [pa.int64()] * 5 + [pa.binary()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(columns, types)], [x.split()[0] for x in schema.split(", ")])

    return docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text")).mapInArrow(run, schema)


def shortest_pack_first(histogram: dict[int, int], size: int = SIZE) -> list[tuple[tuple[int, ...], int]]:
    """(lengths of a pack in order, number of such packs)."""
    open_packs: dict[int, list[tuple[tuple[int, ...], int]]] = defaultdict(list)
    for length in sorted(histogram, reverse=True):
        left = histogram[length]
        while left > 0:
            room = max((r for r, packs in open_packs.items() if packs and r >= length), default=None)
            pattern, count = open_packs[room].pop() if room is not None else ((), left)
            taken = min(left, count)
            if taken < count:
                open_packs[room].append((pattern, count - taken))
            open_packs[(size if room is None else room) - length].append(((*pattern, length), taken))
            left -= taken
    return [pack for packs in open_packs.values() for pack in packs]


def runs_of(patterns: list[tuple[tuple[int, ...], int]]) -> list[tuple[int, int, int, int, int]]:
    """(length, first rank, ranks, first sequence, offset) of every place in every pattern."""
    used: dict[int, int] = defaultdict(int)
    runs, sequence = [], 0
    for pattern, count in patterns:
        offset = 0
        for length in pattern:
            runs.append((length, used[length], count, sequence, offset))
            used[length] += count
            offset += length
        sequence += count
    return runs


def ranked(pieces: DataFrame, bucket_rows: int = 200_000) -> tuple[DataFrame, dict[int, int]]:
    """pieces with a gapless `rank` within their length, and the histogram. Ranks come from counts per (length, bucket) and an order inside
    a bucket, so that a length which holds a third of all pieces is spread over at least 256 groups."""
    histogram = {r["length"]: r["n"] for r in pieces.groupBy("length").agg(F.count(F.lit(1)).alias("n")).collect()}
    buckets = max(256, sum(histogram.values()) // bucket_rows)
    dealt = pieces.withColumn("bucket", F.pmod(F.xxhash64("doc_id", "start", "ids_crc32"), F.lit(buckets)))
    counts = dealt.groupBy("length", "bucket").agg(F.count(F.lit(1)).alias("n"))
    before = Window.partitionBy("length").orderBy("bucket").rowsBetween(Window.unboundedPreceding, -1)
    begins = counts.select("length", "bucket", F.coalesce(F.sum("n").over(before), F.lit(0)).alias("begin"))
    inside = F.row_number().over(Window.partitionBy("length", "bucket").orderBy("doc_id", "start", "ids_crc32"))
    return dealt.withColumn("inside", inside - 1).join(begins, ["length", "bucket"]).withColumn("rank", F.col("begin") + F.col("inside")).drop("bucket", "inside", "begin"), histogram


def packed(docs: DataFrame, vocabulary: str | None = None, size: int = SIZE, id_col: str = "doc_id", text_col: str = "text", with_ids: bool = False) -> DataFrame:
    """One row per piece, with its sequence_id and offset there."""
    pieces = stored(token_pieces(docs, vocabulary or default_vocabulary(), size, id_col, text_col, with_ids), "pieces")
    rows, histogram = ranked(pieces)
    runs = runs_of(shortest_pack_first(histogram, size))
    table = docs.sparkSession.createDataFrame(runs, "length long, first long, ranks long, first_sequence long, offset long")
    # The runs number a few for each length at any input size; only a table of that proven size is broadcast.
    table = F.broadcast(table) if len(runs) <= 64 * size else table
    out = rows.join(table, "length").filter((F.col("rank") >= F.col("first")) & (F.col("rank") < F.col("first") + F.col("ranks")))
    ids = ["ids"] if with_ids else []
    return out.select("doc_id", "start", "length", "ids_crc32", "doc_tokens", (F.col("first_sequence") + F.col("rank") - F.col("first")).alias("sequence_id"), "offset", *ids)


def sequences(pieces: DataFrame, size: int = SIZE) -> DataFrame:
    """(sequence_id, ids array<long>, n_ids): sequences padded with the end id, from packed(..., with_ids=True); a group holds at most `size` ids."""

    def run(batches):
        for batch in batches:
            rows = []
            for sequence, parts in zip(batch.column(0).to_pylist(), batch.column(1).to_pylist()):
                ids = array("I", b"".join(p["ids"] for p in sorted(parts, key=lambda p: p["offset"]))).tolist()
                rows.append((sequence, ids + [END_ID] * (size - len(ids)), len(ids)))
            yield pa.RecordBatch.from_arrays([pa.array([r[k] for r in rows], t) for k, t in enumerate((pa.int64(), pa.list_(pa.int64()), pa.int64()))], ["sequence_id", "ids", "n_ids"])

    grouped = pieces.groupBy("sequence_id").agg(F.collect_list(F.struct("offset", "ids")).alias("parts"))
    return grouped.mapInArrow(run, "sequence_id long, ids array<long>, n_ids long")
