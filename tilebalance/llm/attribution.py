"""Token counts of fields and sections by character offsets.

A document is encoded once, whole; the bytes of its tokens give each token's
character span, and an interval join (two binary searches a token) finds the
sections it touches.  A token that touches several is allocated by a rule:
"first" (the section of its first touched character), "last", or "majority" (most characters, the
earlier of equals).  Tokens that touch none are counted as outside.
"""

from __future__ import annotations

import base64

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

RULES = ("first", "last", "majority")
_ENCODINGS: dict[tuple[str, str], tuple] = {}


def encoding(path: str, pattern: str):
    """(tiktoken encoding, byte length of each id)."""
    if (path, pattern) not in _ENCODINGS:
        import tiktoken

        with open(path, "rb") as f:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
        size = np.zeros(max(ranks.values()) + 1, np.int64)
        for token, k in ranks.items():
            size[k] = len(token)
        _ENCODINGS[path, pattern] = tiktoken.Encoding("own", pat_str=pattern, mergeable_ranks=ranks, special_tokens={}), size
    return _ENCODINGS[path, pattern]


def token_spans(text: str, path: str, pattern: str) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """(ids, first character, character after the last) of a text's tokens; a token that holds part of a character's bytes touches it."""
    enc, size = encoding(path, pattern)
    ids = enc.encode_to_numpy(text).astype(np.int64)
    end = np.cumsum(size[ids])
    begin = end - size[ids]
    if text.isascii() or not len(ids):
        return ids, begin, end
    char = np.cumsum((np.frombuffer(text.encode(), np.uint8) & 0xC0) != 0x80) - 1
    return ids, char[begin], char[end - 1] + 1


def allocate(begin: np.ndarray, end: np.ndarray, sec_begin: np.ndarray, sec_end: np.ndarray, rule: str = "majority") -> tuple[np.ndarray, np.ndarray]:
    """(section of each token or -1, whether it touches several).  Sections are disjoint and in order; empty ones hold no token."""
    if rule not in RULES:
        raise ValueError(f"rule must be one of {RULES}")
    full = np.flatnonzero(sec_end > sec_begin)
    a, b = sec_begin[full], sec_end[full]
    lo = np.searchsorted(b, begin, side="right")
    hi = np.searchsorted(a, end, side="left") - 1
    out = np.where(hi >= lo, lo if rule != "last" else hi, -1)
    crossing = hi > lo
    if rule == "majority":
        for k in np.flatnonzero(crossing):
            own = np.arange(lo[k], hi[k] + 1)
            out[k] = own[np.argmax(np.minimum(end[k], b[own]) - np.maximum(begin[k], a[own]))]
    return np.where(out >= 0, full[np.maximum(out, 0)] if len(full) else -1, -1), crossing


def lines(text: str) -> tuple[np.ndarray, np.ndarray]:
    """Spans of the lines of a text, without their line feeds."""
    feeds = [-1]
    while (k := text.find("\n", feeds[-1] + 1)) >= 0:
        feeds.append(k)
    at = np.array(feeds, np.int64)
    return at + 1, np.append(at[1:], len(text))


def attribute(docs: DataFrame, path: str, pattern: str, id_col: str = "doc_id", fields: tuple[str, ...] = ("text",), joint: str = "\n", by: str = "lines", rule: str = "majority") -> DataFrame:
    """One row per input row: doc_id, n_tokens, n_sections, n_crossing, n_outside, section_tokens.

    by="lines": sections are the lines of the fields joined with `joint`;
    by="fields": the fields themselves.  section_tokens and n_outside add up to
    n_tokens.  Null fields are empty; an empty text has one empty line and no
    token; long texts are encoded whole; repeated rows are repeated; only the
    named columns are read; an empty table gives no rows.
    """
    if by not in ("lines", "fields") or rule not in RULES:
        raise ValueError("unknown sections or rule")

    def run(batches):
        for batch in batches:
            ids, rows = batch.column(0), []
            for parts in zip(*[c.to_pylist() for c in batch.columns[1:]]):
                parts = [p or "" for p in parts]
                text = joint.join(parts)
                if by == "lines":
                    first, after = lines(text)
                else:
                    size = np.array([len(p) for p in parts], np.int64)
                    after = np.cumsum(size + len(joint)) - len(joint)
                    first = after - size
                tokens, a, b = token_spans(text, path, pattern)
                section, crossing = allocate(a, b, first, after, rule)
                counts = np.bincount(section[section >= 0], minlength=len(first))
                rows.append((len(tokens), len(first), int(crossing.sum()), int((section < 0).sum()), counts))
            n, m, c, o, s = zip(*rows) if rows else ([],) * 5
            at = np.concatenate([[0], np.cumsum(np.array(m, np.int64))]).astype(np.int32)
            listed = pa.ListArray.from_arrays(pa.array(at), pa.array(np.concatenate(s).astype(np.int64) if rows else np.zeros(0, np.int64)))
            i = pa.int64()
            yield pa.RecordBatch.from_arrays([ids, pa.array(n, i), pa.array(m, i), pa.array(c, i), pa.array(o, i), listed], names=["doc_id", "n_tokens", "n_sections", "n_crossing", "n_outside", "section_tokens"])

    own = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), *[F.col(f).cast("string").alias(f"f{k}") for k, f in enumerate(fields)])
    return own.mapInArrow(run, "doc_id bigint, n_tokens bigint, n_sections bigint, n_crossing bigint, n_outside bigint, section_tokens array<bigint>")
