"""Secrets in text: three patterns, and strings that zstandard can't explain.

The novelty search looks at strings of key-like characters that follow a sensitive word.  Each is compressed with a
dictionary primed with common identifiers and the code around it; what it costs beyond an empty string is its marginal size.
A string whose marginal size is close to what random text of its alphabet takes repeats nothing near it and is no known identifier: it is reported.
"""

from __future__ import annotations

import hashlib
import math
import re
from collections.abc import Iterator
from typing import NamedTuple

import pyarrow as pa
from pyspark.sql import Column, DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import tidy

#: Kinds in the order in which spans of one start are listed, and the patterns with their least lengths.
KINDS = ("assign", "access", "hex", "novel")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{24,}")  # a maximal run, as + would find it
ASSIGN_MIN, ACCESS_MIN = 6, 20

#: Strings that the novelty search weighs, and how far before them a sensitive word may stand.
CANDIDATE = re.compile(r"[A-Za-z0-9+/_-]{16,}={0,2}")
DELIMITER = re.compile(r"[_-]+")
SENSITIVE = re.compile(r"passw|secret|token|api_?key|credential|bearer|authorization|private.?key|access.?key|signature|client.?id", re.IGNORECASE | re.ASCII)
CONTEXT = 64
SURROUNDING = 2048
#: Least marginal bytes of a string that is reported, as a share of the bytes that random text of its alphabet takes.
NOVELTY = 0.93

#: Identifiers that code shares.
IDENTIFIERS = (
    "access_token refresh_token client_secret client_id api_key apikey secret_key private_key public_key password passwd username "
    "authorization bearer authentication credentials signature session_id request_id user_id account_id database connection "
    "configuration environment function return import export class public static final void string integer boolean default "
    "constructor prototype application/json content-type charset=utf-8 https:// http:// localhost 127.0.0.1 example.com "
    "ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789+/ 0123456789abcdef 1234567890 00000000 xxxxxxxx your_api_key_here "
    "getElementById addEventListener XMLHttpRequest SELECT FROM WHERE INSERT UPDATE DELETE CREATE TABLE PRIMARY KEY"
)


class Span(NamedTuple):
    """Code points start to end (exclusive) of a text."""

    start: int
    kind: str
    end: int

    def __str__(self) -> str:
        return f"{self.kind}:{self.start}:{self.end}"


def _listed(spans: list[Span]) -> list[Span]:
    return sorted(spans, key=lambda s: (s.start, KINDS.index(s.kind)))


def pattern_spans(text: str) -> list[Span]:
    """The three patterns, leftmost and non-overlapping each; matches that are too short are dropped."""
    found = []
    low = text.lower()
    if any(word in low for word in ("password", "passwd", "secret", "token", "api")):
        found += [Span(m.start(), "assign", m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= ASSIGN_MIN]
    if "AKIA" in text:
        found += [Span(m.start(), "access", m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= ACCESS_MIN]
    found += [Span(m.start(), "hex", m.end()) for m in HEX.finditer(text)]
    return _listed(found)


def marginal_bytes(candidate: str, surrounding: str) -> int:
    """Bytes that the candidate adds to an empty frame, given the identifiers and its surroundings."""
    import zstandard

    primed = zstandard.ZstdCompressionDict(f"{IDENTIFIERS} {surrounding}".encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
    compressor = zstandard.ZstdCompressor(level=3, dict_data=primed, write_checksum=False, write_content_size=False)
    return len(compressor.compress(candidate.encode())) - len(compressor.compress(b""))


def random_bytes(candidate: str) -> float:
    """Bytes that a random string of the candidate's length and kinds of characters takes."""
    letters = candidate.rstrip("=")
    if re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", letters):
        size = 16
    else:
        size = sum(n for kind, n in (("[0-9]", 10), ("[a-z]", 26), ("[A-Z]", 26)) if re.search(kind, letters)) + len(set(letters) & set("+/_-"))
    return len(letters) * math.log2(max(2, size)) / 8


def novel_spans(text: str) -> list[Span]:
    """Incompressible strings in sensitive context."""
    ends = [m.end() for m in SENSITIVE.finditer(text)]
    found, done = [], 0
    for end in ends:
        value = m.end() if (m := DELIMITER.match(text, end)) else end
        for m in CANDIDATE.finditer(text, max(value, done), min(len(text), value + CONTEXT)):
            if m.start() > 0 and CANDIDATE.match(text[m.start() - 1] * 16) and not m.start() == value > end:
                continue  # the rest of a longer string, whose start is no candidate
            start, stop = m.start(), CANDIDATE.match(text, m.start()).end()
            done, own = stop, text[start:stop]
            if not any(c.isalpha() for c in own):
                continue
            around = f"{text[max(0, start - SURROUNDING) : start]} {text[stop : stop + SURROUNDING]}"
            if marginal_bytes(own, around) >= NOVELTY * random_bytes(own):
                found.append(Span(start, "novel", stop))
    return _listed(found)


def find_secrets(text: str | None) -> list[Span]:
    """All spans in order: the patterns', and novel ones outside of them.  None in a null or empty text."""
    if not text:
        return []
    base = pattern_spans(text)
    return _listed(base + [s for s in novel_spans(text) if not any(b.start <= s.start and s.end <= b.end for b in base)])


def redact(text: str | None, mark: str = "<SECRET>") -> str | None:
    """The text with each stretch of (possibly overlapping) spans replaced by a mark."""
    spans = find_secrets(text)
    if not spans:
        return text
    out, at = [], 0
    for s in spans:
        if s.start >= at:
            out += [text[at : s.start], mark]
        at = max(at, s.end)
    return "".join([*out, text[at:]])


def scan(docs: DataFrame, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, spans): an array of (kind, start, end) for every row.  Null texts are empty; repeated rows stay repeated."""

    def each(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64())]))
        for batch in batches:
            spans = [[{"kind": s.kind, "start": s.start, "end": s.end} for s in find_secrets(t.as_py())] for t in batch["text"]]
            yield pa.record_batch([batch["doc_id"], pa.array(spans, kind)], names=["doc_id", "spans"])

    return docs.select(F.col(doc_id).alias("doc_id"), F.col(text).alias("text")).mapInArrow(tidy(each), f"doc_id {docs.schema[doc_id].dataType.simpleString()}, spans array<struct<kind:string,start:long,end:long>>")


def redact_secrets(docs: DataFrame) -> DataFrame:
    """``docs`` with secrets in the column text replaced by a mark, and n_chars (if there) counted anew where they were.  A null
    text stays null, other columns stay as they are, and rows are taken one by one, repeated or not."""
    schema = ", ".join(f"`{f.name}` {f.dataType.simpleString()}" for f in docs.schema)

    def redacted(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            texts = batch["text"].to_pylist()
            clean = [redact(t) for t in texts]
            columns = dict(zip(batch.schema.names, batch.columns, strict=True))
            columns["text"] = pa.array(clean, batch.schema.field("text").type)
            if "n_chars" in columns:
                sizes = columns["n_chars"].to_pylist()
                columns["n_chars"] = pa.array([n if t == c else len(c) for t, c, n in zip(texts, clean, sizes, strict=True)], batch.schema.field("n_chars").type)
            yield pa.record_batch(list(columns.values()), names=list(columns))

    return docs.mapInArrow(tidy(redacted), schema)


def op6_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    """Secrets in every document."""
    found = scan(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    base = F.filter("spans", lambda s: s["kind"] != "novel")

    def joined(spans: Column) -> Column:
        return F.array_join(F.transform(spans, lambda s: F.concat_ws(":", s["kind"], s["start"].cast("string"), s["end"].cast("string"))), ",")

    def counted(kind: str) -> Column:
        return F.size(F.filter("spans", lambda s: s["kind"] == kind)).cast("long").alias(f"n_{kind}")

    counts = [counted(k) for k in KINDS]
    return found.select("doc_id", *counts[:3], F.sha2(joined(base), 256).alias("base_sha256"), joined(F.col("spans")).alias("spans"), counts[3])
