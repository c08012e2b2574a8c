"""Token counts by section, from one encoding of each whole text.

Tokens of a byte-level vocabulary are byte strings, so the spans of the tokens in a text
follow from their lengths. The spans are joined with the sections' spans by their order
(a binary search for each boundary); a token across a boundary is allocated by a rule:
"start": to the section of its first byte; "most": to the section with most of its bytes,
the earlier on a tie; "share": to each by its share of the bytes.
"""

from __future__ import annotations

import base64
from itertools import pairwise

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame

RULES = ("start", "most", "share")
VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
# Fixed value: the pattern that the public 50k byte-level vocabulary splits text by.
PATTERN = r"'s|'t|'re|'ve|'m|'ll|'d| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"


class Encoder:
    """Token ids of a text, and how many bytes each token has."""

    def __init__(self, ranks: dict[bytes, int], pattern: str = PATTERN):
        import tiktoken

        self.encoding = tiktoken.Encoding("byte level", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})
        self.lengths = np.zeros(max(ranks.values(), default=-1) + 1, np.int64)
        for token, i in ranks.items():
            self.lengths[i] = len(token)

    def ends(self, text: str) -> np.ndarray:
        """Where each token ends, in bytes of UTF-8."""
        ids = self.encoding.encode_ordinary(text) if text else []
        return np.cumsum(self.lengths[np.array(ids, np.int64)])


def read_ranks(path: str) -> dict[bytes, int]:
    with open(path, "rb") as f:
        return {base64.b64decode(token): int(rank) for token, rank in map(bytes.split, filter(None, map(bytes.strip, f)))}


def line_sections(text: bytes) -> list[tuple[str, int, int]]:
    """(name, start, end) in bytes: the first line is the head, the last of several the foot, all between the body. Line ends belong to the line before."""
    if not text:
        return []
    first = text.find(b"\n") + 1 or len(text)
    last = max(text.rstrip(b"\n").rfind(b"\n") + 1, first)
    return [(n, s, e) for n, s, e in (("head", 0, first), ("body", first, last), ("foot", last, len(text))) if e > s]


def allocate(ends: np.ndarray, sections: list[tuple[str, int, int]], rule: str = "start") -> list[float]:
    """Tokens of each section; sections are in order and don't overlap. What no section holds goes nowhere."""
    starts = np.r_[0, ends[:-1]] if len(ends) else ends
    out = []
    if rule == "start":
        edges = np.searchsorted(starts, [[s, e] for _, s, e in sections]) if sections else []
        return [float(b - a) for a, b in edges]
    shares = np.zeros((len(sections), len(ends)))
    lengths = np.maximum(ends - starts, 1)
    for i, (_, s, e) in enumerate(sections):
        a, b = np.searchsorted(ends, s, "right"), np.searchsorted(starts, e, "left")
        shares[i, a:b] = (np.minimum(ends[a:b], e) - np.maximum(starts[a:b], s)) / lengths[a:b]
    if rule == "share":
        return shares.sum(1).tolist()
    if rule != "most":
        raise ValueError(f"rule is none of {RULES}")
    held = shares.max(0) > 0 if len(sections) else np.zeros(0, bool)
    best = shares.argmax(0)[held] if len(sections) else []
    out = np.bincount(best, minlength=len(sections)).astype(float).tolist()
    return out


def character_spans(text: str, ends: np.ndarray) -> list[tuple[int, int]]:
    """(start, end) of each token in code points: those that its bytes touch."""
    data = np.frombuffer(text.encode("utf-8", "surrogatepass"), np.uint8)
    number = np.cumsum((data & 0xC0) != 0x80) - 1
    return [(int(number[s]), int(number[e - 1]) + 1) for s, e in pairwise([0, *ends.tolist()])]


_SCHEMA = pa.schema([("doc_id", pa.int64()), ("n_tokens", pa.int64()), ("sections", pa.list_(pa.struct([("section", pa.string()), ("first_byte", pa.int64()), ("n_bytes", pa.int64()), ("n_tokens", pa.float64())])))])


def section_tokens(docs: DataFrame, vocabulary: str = VOCABULARY, rule: str = "start", sections=line_sections) -> DataFrame:
    """One row per row of docs(doc_id BIGINT, text): doc_id, n_tokens, sections.

    sections has (section, first_byte, n_bytes, n_tokens) for each section of the text; with
    "start" or "most" they sum up to n_tokens. Null and empty texts have no tokens and no
    sections. Repeated rows get a row each. Other columns are ignored. The vocabulary is read
    on the driver and sent to each worker once.
    """
    if rule not in RULES:
        raise ValueError(f"rule is none of {RULES}")
    ranks = docs.sparkSession.sparkContext.broadcast(read_ranks(vocabulary))

    def run(batches):
        encoder = None
        for batch in batches:
            for at in range(0, batch.num_rows, 128):
                part = batch.slice(at, 128)
                encoder = encoder or Encoder(ranks.value)
                n_tokens, found = [], []
                for text in part.column(1).to_pylist():
                    ends = encoder.ends(text or "")
                    own = sections((text or "").encode())
                    n_tokens.append(len(ends))
                    found.append([{"section": n, "first_byte": s, "n_bytes": e - s, "n_tokens": k} for (n, s, e), k in zip(own, allocate(ends, own, rule), strict=True)])
                yield pa.RecordBatch.from_arrays([part.column(0), pa.array(n_tokens, pa.int64()), pa.array(found, _SCHEMA.field(2).type)], schema=_SCHEMA)

    kind = "doc_id long, n_tokens long, sections array<struct<section:string,first_byte:long,n_bytes:long,n_tokens:double>>"
    return docs.selectExpr("CAST(doc_id AS BIGINT) AS doc_id", "CAST(text AS STRING) AS text").mapInArrow(run, kind)
