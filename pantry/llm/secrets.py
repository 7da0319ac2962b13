"""Secret scans: patterns, and a token-efficiency test.

Three patterns give the base spans. The method adds spans of kind ``random``: a run of characters that
keys are made of costs many tokens of a public byte-pair vocabulary for its length if it is random,
few if it is language. Runs are tested once a batch each, whole and in pieces between separators; digests
of known lengths, UUIDs and runs without letters are excluded first, as are spans that a base span covers.

The vocabulary (a .tiktoken file; the path on the driver is a parameter) is sent to the executors and read
once a worker. All work is linear in the text: separators are no part of a piece, pieces are looked at up
to a run's least length ahead, tokens are counted a thousand characters at a time.

Defined results: null and empty texts have no spans; positions are code points, ends exclusive; texts
are scanned whole; repeated rows have a row each; an empty table gives an empty result.
"""

from __future__ import annotations

import base64
import bisect
import functools
import hashlib
import itertools
import os
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

VOCABULARY = "/opt/tokenizers/byte_bpe_50k.tiktoken"
KINDS = ("assign", "access", "hex", "random")

#: Fixed values.
ASSIGN = re.compile(r"(password|passwd|secret|token|api_?key)[\"']?\x20*[:=]\x20*[\"']?([A-Za-z0-9+/_.=-]+)", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
HEX_LONG = re.compile(r"[0-9a-f]{32,}")
ASSIGN_HINTS = ("password", "passwd", "secret", "token", "api")

RUN = re.compile(r"[A-Za-z0-9+/_=-]{20,}")
DIGEST = re.compile(r"(?:[0-9a-fA-F]{32}|[0-9a-fA-F]{40}|[0-9a-fA-F]{56}|[0-9a-fA-F]{64}|[0-9a-fA-F]{96}|[0-9a-fA-F]{128})\Z")
UUID = re.compile(r"[0-9a-fA-F]{8}-(?:[0-9a-fA-F]{4}-){3}[0-9a-fA-F]{12}\Z")
PIECE = re.compile(r"(?<![A-Za-z0-9])[0-9a-fA-F]{8}-(?:[0-9a-fA-F]{4}-){3}[0-9a-fA-F]{12}(?![A-Za-z0-9])|[A-Za-z0-9+]+")
LEAST = 20
WINDOW = 1000


@functools.cache
def encoder(path: str):
    """The public vocabulary as a tiktoken encoding."""
    import tiktoken

    with open(path, "rb") as lines:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
    pattern = r"""'(?:[sdmt]|ll|ve|re)| ?\p{L}+| ?\p{N}+| ?[^\s\p{L}\p{N}]+|\s+(?!\S)|\s+"""
    return tiktoken.Encoding("public", pat_str=pattern, mergeable_ranks=ranks, special_tokens={})


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the three patterns."""
    out = []
    low = text.lower() if text.isascii() else text.casefold()
    if any(h in low for h in ASSIGN_HINTS):
        out += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 8]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 16]
    out += [(m.start(), 2, m.end()) for m in HEX_LONG.finditer(text)]
    return out


def excluded(run: str) -> bool:
    """Known digests and identifiers, and numbers: what is no secret although it is dense."""
    return not any(c.isalpha() for c in run) or bool(DIGEST.match(run) or UUID.match(run))


def dense_spans(run: str, dense) -> list[tuple[int, int]]:
    """(start, end) in a run: all of it, or the pieces between separators that are dense by themselves.

    Text around a key does not thin it out: each piece is tested with as many of the next as make a run's
    least length, none across a digest or identifier; spans that overlap are one.
    """
    if excluded(run):
        return []
    pieces = [(m.start(), m.end(), excluded(m[0]) and m.end() - m.start() >= LEAST) for m in PIECE.finditer(run)]
    if not any(known for *_, known in pieces) and dense(run):
        return [(0, len(run))]
    out: list[tuple[int, int]] = []
    for i, (a, _, _) in enumerate(pieces):
        for k in range(i, len(pieces)):  # LEAST pieces at most
            _, b, known = pieces[k]
            if known:
                break
            if b - a >= LEAST:
                if not excluded(run[a:b]) and dense(run[a:b]):
                    if out and a < out[-1][1]:
                        out[-1] = (out[-1][0], max(b, out[-1][1]))
                    else:
                        out.append((a, b))
                break
    return out


def tokens(part: str, vocabulary: str) -> int:
    """Tokens of a part, a thousand characters at a time: byte-pair merging takes more than linear time."""
    encode = encoder(vocabulary).encode_ordinary
    return sum(len(encode(part[i : i + WINDOW])) for i in range(0, len(part), WINDOW))


def random_spans(text: str, vocabulary: str, ratio: float, seen: dict[str, list]) -> list[tuple[int, int, int]]:
    dense = lambda part: len(part) / tokens(part, vocabulary) < ratio
    out = []
    for m in RUN.finditer(text):
        run = m[0]
        found = seen.get(run)
        if found is None:
            found = seen[run] = dense_spans(run, dense)
        out += [(m.start() + a, 3, m.start() + b) for a, b in found]
    return out


def shown(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for a, k, b in sorted(spans))


def scan_text(text: str | None, vocabulary: str = VOCABULARY, ratio: float = 1.9, seen: dict[str, list] | None = None) -> tuple[list, list]:
    """(base spans, added spans) of one text."""
    text = text or ""
    base = base_spans(text)
    extra = random_spans(text, vocabulary, ratio, {} if seen is None else seen)
    base.sort()
    reach = list(itertools.accumulate((e for _, _, e in base), max))  # the farthest end of the first spans
    before = lambda s: bisect.bisect_right(base, (s[0], len(KINDS), 0))
    return base, [s for s in extra if not before(s) or reach[before(s) - 1] < s[2]]


def scan(df: DataFrame, vocabulary: str = VOCABULARY, ratio: float = 1.9, doc_id: str = "doc_id", text: str = "text") -> DataFrame:
    """(doc_id, spans array<struct<kind, start, end, value>>, base_sha256); the vocabulary goes to the executors with the job."""
    df.sparkSession.sparkContext.addFile(vocabulary)
    name = os.path.basename(vocabulary)

    def run(batches):
        from pyspark import SparkFiles

        own = SparkFiles.get(name)
        for b in batches:
            rows, digests, seen = [], [], {}
            for t in b.column(1).to_pylist():
                base, extra = scan_text(t, own, ratio, seen)
                rows.append([{"kind": KINDS[k], "start": a, "end": e, "value": t[a:e]} for a, k, e in sorted(base + extra)])
                digests.append(hashlib.sha256(shown(base).encode()).hexdigest())
            kind = pa.list_(pa.struct([("kind", pa.string()), ("start", pa.int64()), ("end", pa.int64()), ("value", pa.string())]))
            yield pa.RecordBatch.from_arrays([b.column(0), pa.array(rows, kind), pa.array(digests, pa.string())], ["doc_id", "spans", "base_sha256"])

    slim = df.select(F.col(f"`{doc_id}`").alias("doc_id"), F.col(f"`{text}`").alias("text"))
    kind = dict(slim.dtypes)["doc_id"]
    return slim.mapInArrow(run, f"doc_id {kind}, spans array<struct<kind:string,start:bigint,end:bigint,value:string>>, base_sha256 string")
