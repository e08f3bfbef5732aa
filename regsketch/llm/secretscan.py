"""Secrets in text: known forms, and random strings that a tokenizer cannot compress.

Ordinary words and identifiers take few tokens for their characters; random strings
take nearly one for every two. A run of token-like characters with fewer
characters a token than ``RATIO`` is reported unless it is a known digest or identifier:
hexadecimal of a digest's length, a UUID, digits alone, or a part of an e-mail or web address other than a query.

Defined results: a null or empty text has no spans; matches of a base form that are
too short are dropped and not retried from within; base spans always stay, others where they do
not overlap a base span; repeated rows give repeated results, an empty table none;
extra columns are ignored. Offsets are code points, end exclusive.
"""

from __future__ import annotations

import base64
import re
from collections.abc import Iterator

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ..plans.ship import map_arrow
from .textbatch import slices

#: Characters a token, below which a run is random; shortest run that is judged.
RATIO, SHORTEST = 2.2, 16
#: Letters of one case, shorter than which a run is taken for a word: rare words have as few characters a token.
WORD = 24

#: Forms of secrets and of known strings.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.ASCII | re.IGNORECASE)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]{16,}")
RUN = re.compile(r"[A-Za-z0-9+/_=-]{16,}")
ASSIGN_WORDS = ("pass", "secret", "token", "api")
DIGEST_LENGTHS = (32, 40, 56, 64, 96, 128)
UUID = re.compile(r"[0-9a-fA-F]{8}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{4}-[0-9a-fA-F]{12}")
KINDS = ("assign", "access", "hex", "random")

_encodings: dict = {}


def encoding(path: str):
    """The vocabulary of a file of ranks; its pattern leaves a run of token-like characters whole, so that only merges count."""
    if path not in _encodings:
        import tiktoken

        with open(path, "rb") as lines:
            ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, lines)}
        _encodings[path] = tiktoken.Encoding("secrets", pat_str=r"[A-Za-z]+|[0-9]+|[^A-Za-z0-9]+", mergeable_ranks=ranks, special_tokens={})
    return _encodings[path]


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind, end) of the three base forms, kinds as numbers in their order."""
    found = []
    low = text.lower()
    if any(w in low for w in ASSIGN_WORDS):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m[2]) >= 12]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if len(m[0]) >= 18]
    found += [(m.start(), 2, m.end()) for m in HEX.finditer(text)]
    return sorted(found)


def known(run: str, before: str, after: str) -> bool:
    """Whether a run is a digest, an identifier, plain words or a part of an address."""
    if UUID.search(run) or not re.search("[A-Za-z]", run):
        return True
    if len(run) in DIGEST_LENGTHS and re.search("[0-9]", run) and re.fullmatch(r"[0-9a-f]+|[0-9A-F]+", run):
        return True
    if len(run) < WORD and run.isalpha() and (run[1:].islower() or run.isupper()):
        return True
    joined = re.search(r"\S*$", before)[0]  # what the run continues without a space
    if "://" in joined + run:
        return "?" not in joined  # values of a query are judged
    if joined.endswith("."):
        return not re.search(r"[A-Za-z0-9+/_=-]{16}\.$", joined)  # parts of a dotted token are judged
    return joined.endswith("@") or after == "@"


def random_spans(text: str, coder, ratio: float = RATIO) -> list[tuple[int, int, int]]:
    """(start, kind, end) of runs with few characters a token."""
    found = []
    for m in RUN.finditer(text):
        run = m[0]
        if known(run, text[max(0, m.start() - 64) : m.start()], text[m.end() : m.end() + 1]):
            continue
        if len(run) / len(coder.encode_ordinary(run)) < ratio:
            found.append((m.start(), 3, m.end()))
    return found


def scan(docs: DataFrame, vocabulary: str, ratio: float = RATIO) -> DataFrame:
    """(doc_id, spans): for each document the list of (start, kind, end), by start, then kind as in KINDS."""

    def find(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        coder = encoding(vocabulary)
        for whole in batches:
            for batch in slices(whole):
                out = []
                for text in batch.column("text").to_pylist():
                    base = base_spans(text or "")
                    more = [x for x in random_spans(text or "", coder, ratio) if not any(b[0] < x[2] and x[0] < b[2] for b in base)]
                    out.append([{"start": s, "kind": KINDS[k], "end": e} for s, k, e in sorted(base + more)])
                kind = pa.list_(pa.struct([("start", pa.int32()), ("kind", pa.string()), ("end", pa.int32())]))
                yield pa.RecordBatch.from_arrays([batch.column("doc_id"), pa.array(out, kind)], names=["doc_id", "spans"])

    return map_arrow(docs.select(F.col("doc_id").cast("bigint").alias("doc_id"), F.col("text").cast("string").alias("text")), find, "doc_id bigint, spans array<struct<start:int,kind:string,end:int>>")
