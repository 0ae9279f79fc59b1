"""Hashed text features shared by the two text classifiers, and the bounded training sample."""

from __future__ import annotations

import zlib

import numpy as np
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

#: Maps bytes to lower case and everything that is no ASCII letter, digit or non-ASCII byte to a space.
_WORD_BYTES = bytes(b + 32 if 65 <= b <= 90 else b if 48 <= b <= 57 or 97 <= b <= 122 or b >= 128 else 32 for b in range(256))
#: Maps bytes to their kind: letters, capitals, digits, non-ASCII as lower case; signs and white space stay.
_KIND_BYTES = bytes(65 if 65 <= b <= 90 else 97 if 97 <= b <= 122 or b >= 128 else 48 if 48 <= b <= 57 else b for b in range(256))


def hashes(tokens: list[bytes]) -> np.ndarray:
    return np.fromiter(map(zlib.crc32, tokens), np.uint64, len(tokens))


def words(text: str | None) -> list[bytes]:
    return (text or "").encode("utf-8", "surrogatepass").translate(_WORD_BYTES).split()


def shapes(text: str | None) -> list[bytes]:
    """Each white-space token with runs of one character kind collapsed, such as `Aa.` or `a#`."""
    kinds = np.frombuffer((text or "").encode("utf-8", "surrogatepass").translate(_KIND_BYTES), np.uint8)
    return kinds[np.flatnonzero(np.diff(kinds, prepend=kinds[:1] ^ 1))].tobytes().split() if len(kinds) else []


def labelled_sample(docs: DataFrame, labels: DataFrame, columns: list[str], rows: int, longest: int, trained_on=None) -> list:
    """At most `rows` labelled rows with texts of at most `longest` characters, the same ones at each run: those with the smallest digests of their ids.

    trained_on: a condition on labels' doc_id. Repeated labels of one id count once, by their largest value. This bound on training is the only sample taken.
    """
    graded = labels.filter(F.col("doc_id").isNotNull())
    graded = graded.filter(trained_on) if trained_on is not None else graded
    graded = graded.groupBy("doc_id").agg(*(F.max(c).alias(c) for c in columns)).dropna()
    chosen = graded.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id").limit(rows)
    texts = docs.select("doc_id", "text").filter(F.col("text").isNotNull() & (F.length("text") <= longest))
    got = texts.join(F.broadcast(chosen), "doc_id")  # at most `rows` ids
    # Repeated ids can bring more rows than ids: only the first `rows` rows of one order, of at most `longest` characters each, reach the driver.
    got = got.orderBy(F.md5(F.col("doc_id").cast("string")), "doc_id", F.crc32(F.col("text").cast("binary")), "text").limit(rows).collect()
    return sorted(got, key=lambda r: (zlib.crc32(str(r["doc_id"]).encode()), r["doc_id"], r["text"]))
