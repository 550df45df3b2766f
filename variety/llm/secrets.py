"""Secrets in texts: three patterns, and a token-efficiency test for random strings.

A vocabulary learnt on text covers words with few tokens and random strings with many.
Strings of few characters a token are reported, unless they are digests, UUIDs or
numbers, or overlap a pattern's span.
"""

from __future__ import annotations

import hashlib
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession
from pyspark.sql import functions as F

from .common import slices, table, text_frame
from .tokens import byte_pair_encoder, vocabulary_path

KINDS = ("assign", "access", "hex", "token")
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ASSIGN_WORDS = ("passw", "secret", "token", "apikey", "api_key")
ACCESS = re.compile(r"AKIA[A-Z0-9]{12,}")
HEX = re.compile(r"[0-9a-f]{32,}")
CANDIDATE = re.compile(r"[A-Za-z0-9+/_-]{20,}={0,2}")
#: Lengths of MD5, SHA-1, SHA-224, SHA-256, SHA-384 and SHA-512 in hexadecimal.
DIGEST_LENGTHS = frozenset({32, 40, 56, 64, 96, 128})
HEX_ONLY = re.compile(r"[0-9a-f]+|[0-9A-F]+")
UUID = re.compile(r"[0-9a-fA-F]{8}(-[0-9a-fA-F]{4}){3}-[0-9a-fA-F]{12}")
MOST_CHARS_PER_TOKEN = 2.2
REDACTED = "[SECRET]"


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind's index, end) of the three patterns' matches."""
    found = []
    low = text.lower()
    if any(w in low for w in ASSIGN_WORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 8]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text)]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    found.sort()
    return found


def random_spans(text: str, known: list[tuple[int, int, int]], encode, most: float = MOST_CHARS_PER_TOKEN) -> list[tuple[int, int, int]]:
    """Spans of strings with fewer than ``most`` characters a token, clear of the known spans."""
    found, i = [], 0
    for m in CANDIDATE.finditer(text):
        s = m.group()
        while i < len(known) and known[i][2] <= m.start():
            i += 1
        if any(a < m.end() and m.start() < b for a, _, b in known[i : i + 4]):
            continue
        digit = any(c in "0123456789" for c in s)
        if not digit and (s == s.lower() or s == s.upper() or s == s.capitalize()):
            continue  # letters of one case are words, however odd
        if s.isdigit() or (HEX_ONLY.fullmatch(s) and len(s) in DIGEST_LENGTHS) or UUID.fullmatch(s):
            continue
        if len(s) < most * len(encode(s)):
            found.append((m.start(), 3, m.end()))
    return found


def joined(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in spans)


def _scan(vocabulary: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_pair_encoder(vocabulary).encode_ordinary
        for batch in slices(batches):
            counts, bases, spans = ([], [], []), [], []
            for text in batch.column(1).to_pylist():
                text = text or ""
                base = base_spans(text)
                for k in range(3):
                    counts[k].append(sum(x[1] == k for x in base))
                bases.append(joined(base))
                spans.append(joined(sorted(base + random_spans(text, base, encode))))
            yield pa.RecordBatch.from_arrays(
                [batch.column(0), *(pa.array(c, pa.int64()) for c in counts), pa.array(bases), pa.array(spans)],
                ["doc_id", "n_assign", "n_access", "n_hex", "base", "spans"],
            )

    return run


def find_secrets(docs: DataFrame, vocabulary: str | None = None) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base and spans for each row of ``docs`` (doc_id, text).

    A span is kind:start:end in code points, the end exclusive, ordered by start and then
    kind (assign, access, hex, token); ``base`` has the first three kinds, ``spans`` all.
    Null and empty texts have none. Rows are judged each for itself: copies, ties and null
    doc_ids need no rule. No shuffle.
    """
    texts = text_frame(docs, F.col("doc_id").cast("long").alias("doc_id"))
    return texts.mapInArrow(_scan(vocabulary or vocabulary_path("byte_bpe_50k.tiktoken")), "doc_id long, n_assign long, n_access long, n_hex long, base string, spans string")


def _redact(vocabulary: str):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encode = byte_pair_encoder(vocabulary).encode_ordinary
        for batch in slices(batches):
            at = batch.schema.get_field_index("text")
            out = []
            for text in batch.column(at).to_pylist():
                if text:
                    base = base_spans(text)
                    parts, done = [], 0
                    for a, _, b in sorted(base + random_spans(text, base, encode)):
                        if a >= done:
                            parts += [text[done:a], REDACTED]
                        done = max(done, b)
                    text = "".join([*parts, text[done:]]) if parts else text
                out.append(text)
            yield batch.set_column(at, "text", pa.array(out, batch.schema.field(at).type))

    return run


def redact_secrets(spark: SparkSession, docs: DataFrame, sf_dir: str) -> DataFrame:
    """Pipeline stage: every secret's span gives way to a fixed mark; all documents stay."""
    clean = docs.mapInArrow(_redact(vocabulary_path("byte_bpe_50k.tiktoken")), docs.schema)
    return clean.withColumn("n_chars", F.length("text").cast(docs.schema["n_chars"].dataType)) if "n_chars" in docs.columns else clean


def op2_secret_scan(spark: SparkSession, sf_dir: str) -> DataFrame:
    found = find_secrets(table(spark, sf_dir, "documents"))
    return found.select("doc_id", "n_assign", "n_access", "n_hex", F.sha2(F.col("base").cast("binary"), 256).alias("base_sha256"), "spans")


def sha256_of(text: str) -> str:
    return hashlib.sha256(text.encode()).hexdigest()
