"""Token counts by offset-mapped attribution.

A document is encoded once, whole, so its tokens are those that training sees. The
tokens' byte lengths give their spans, and the spans meet the document's sections in
an interval join: both are sorted, so a search places each token. A token that lies
across a border is given by one of four rules: ``first`` (the section of its first
byte), ``last`` (of its last byte), ``most`` (the one with most of its bytes; ties go
to the earlier) or ``share`` (each section gets the share of its bytes).

Results by case: a null or empty text is one empty section with no tokens; equal rows
get equal results, one for each; an empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import base64
from collections.abc import Callable, Iterator
from functools import lru_cache
from pathlib import Path

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame, SparkSession

from . import _symbols as S
from ._common import table

RULES = ("first", "last", "most", "share")
COUNTS = "doc_id long, section int, start_byte long, n_bytes long, n_tokens double, n_crossing long"


def vocabulary(path: str | None = None) -> tuple[bytes, str]:
    """Content of a file of byte-pair ranks (1 MB or so) and the pattern that splits texts before it."""
    import public_tokenizers

    return Path(path or public_tokenizers.path("byte_bpe_50k.tiktoken")).read_bytes(), public_tokenizers.PATTERN


@lru_cache(maxsize=2)
def _encoder(ranks: bytes, pattern: str):
    import tiktoken

    table = {base64.b64decode(a): int(b) for a, b in map(bytes.split, ranks.splitlines()) if a}
    size = np.zeros(max(table.values()) + 1, np.int64)
    for token, i in table.items():
        size[i] = len(token)
    return tiktoken.Encoding("ranks", pat_str=pattern, mergeable_ranks=table, special_tokens={}), size


def line_sections(raw: np.ndarray) -> np.ndarray:
    """First bytes of the sections of a text: its lines, each with the line break that ends it."""
    at = np.flatnonzero(raw == 0x0A) + 1
    return np.r_[0, at[at < len(raw)]]


def allocate(ends: np.ndarray, sections: np.ndarray, n_bytes: int, rule: str) -> tuple[np.ndarray, np.ndarray]:
    """Tokens and crossing tokens of each section, from the tokens' ends and the sections' first bytes."""
    starts = np.r_[0, ends[:-1]] if len(ends) else ends
    m = len(sections)
    a = np.searchsorted(sections, starts, "right") - 1
    b = np.searchsorted(sections, ends - 1, "right") - 1
    crossing = np.bincount(a[a != b], minlength=m)
    if rule == "first":
        return np.bincount(a, minlength=m).astype(float), crossing
    if rule == "last":
        return np.bincount(b, minlength=m).astype(float), crossing
    out = np.bincount(a[a == b], minlength=m).astype(float)
    limits = np.r_[sections, n_bytes]
    for i in np.flatnonzero(a != b):
        part = np.arange(a[i], b[i] + 1)
        own = np.minimum(ends[i], limits[part + 1]) - np.maximum(starts[i], limits[part])
        if rule == "most":
            out[part[own.argmax()]] += 1
        else:
            out[part] += own / own.sum()
    return out, crossing


def _count(ranks: bytes, pattern: str, rule: str, sections_of: Callable[[np.ndarray], np.ndarray]):
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        encoder, size = _encoder(ranks, pattern)
        for b in (x for y in batches for x in S.slices(y)):
            raw, at = S.raw_texts(b.column(1))
            texts = b.column(1).to_pylist()
            number, section, start, length, tokens, crossing = [], [], [], [], [], []
            for i, t in enumerate(texts):
                own = raw[at[i] : at[i + 1]]
                ends = np.cumsum(size[encoder.encode_ordinary(t)]) if t else np.zeros(0, np.int64)
                if len(ends) and ends[-1] != len(own):
                    raise ValueError("the tokens do not spell the text")
                s = sections_of(own)
                n, c = allocate(ends, s, len(own), rule)
                number.append(np.full(len(s), i))
                section.append(np.arange(len(s)))
                start.append(s)
                length.append(np.diff(np.r_[s, len(own)]))
                tokens.append(n)
                crossing.append(c)
            cat = np.concatenate
            yield pa.record_batch(
                [b.column(0).take(pa.array(cat(number))), pa.array(cat(section).astype(np.int32)), pa.array(cat(start)), pa.array(cat(length)), pa.array(cat(tokens)), pa.array(cat(crossing))],
                names=["doc_id", "section", "start_byte", "n_bytes", "n_tokens", "n_crossing"],
            )

    return run


def section_tokens(docs: DataFrame, rule: str = "first", tokenizer_path: str | None = None, sections_of: Callable[[np.ndarray], np.ndarray] = line_sections) -> DataFrame:
    """A row for each section of each document: its bytes, tokens by ``rule`` and the crossing tokens that begin in it."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    rows = docs.selectExpr("cast(doc_id as long) as doc_id", "cast(text as string) as text")
    return rows.mapInArrow(_count(*vocabulary(tokenizer_path), rule, sections_of), COUNTS)


def op5_token_counts(spark: SparkSession, sf_dir: str) -> DataFrame:
    return section_tokens(table(spark, sf_dir, "documents"), "first").selectExpr("doc_id", "section", "start_byte", "n_bytes", "cast(n_tokens as long) as n_tokens", "n_crossing")
