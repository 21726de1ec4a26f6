"""Secret scans: fixed base patterns, and dictionary-primed zstandard novelty for what they miss.

Base spans (assign, access, hex) follow fixed patterns and always stay.  Near a sensitive word, a run of key-like
characters is a candidate.  Its novelty is the number of bytes it adds to the compressed surroundings, with a
dictionary of identifiers and the surrounding text as what the compressor already knows, over its length: names and
words repeat the dictionary or the text, random keys do not.  Candidates of high novelty that mix character classes are reported as ``novel``.
A candidate has 16 characters or more, without an upper bound, and a digit among them: runs of letters alone are never
reported.  The compressor packs a long random run to the bits of its alphabet, so beyond ``SHORT`` characters the
novelty asked for is a share of those bits.

Offsets are in code points; null texts count as empty; each row is read on its own.  Every pattern is linear in the text.
"""

from __future__ import annotations

import hashlib
import math
import re

import pyarrow as pa
from pyspark.sql import DataFrame

from .common import col, map_text, narrow, texts

KINDS = ("assign", "access", "hex", "novel")
ASSIGN = re.compile(r"""(?:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.I | re.A)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"(?<![0-9a-f])[0-9a-f]{16,}")
LONG = re.compile(r"(?<![A-Za-z0-9+/_=-])[A-Za-z0-9+/_=-]{16,}+")
# Words near which a key-like run is looked at, and identifiers that prime the compressor.
SENSITIVE = "password passwd secret token apikey api_key access_key private_key credential bearer authorization auth_key passphrase client_key signing_key".split()
KNOWN = "password secret token api_key apiKey access_key accessKeyId secretAccessKey private_key client_secret clientId authorization bearer credential config environment settings database connection string username hostname localhost example default function return import export public static final class const value result request response header content type application json http https www com org version number error message index length object array boolean integer null undefined true false test sample placeholder changeme your_key_here xxxxxxxxxxxxxxxx 0123456789abcdef ABCDEFGHIJKLMNOPQRSTUVWXYZ abcdefghijklmnopqrstuvwxyz license creative commons general public"
BEFORE, AROUND, NOVEL = 80, 400, 0.8
SHORT, OF_BITS = 200, 0.9
_HEX_RUN = bytes(1 if chr(i) in "0123456789abcdef" else 0 for i in range(256))


def base_spans(text: str, raw: bytes, lowered: bytes) -> list[tuple[int, int, str]]:
    """The base spans as (start, end, kind), by start and then kind as listed."""
    found = []
    if any(w in lowered for w in (b"password", b"passwd", b"secret", b"token", b"apikey", b"api_key")):
        found += [(*m.span(), "assign") for m in ASSIGN.finditer(text) if len(m[1]) >= 12]
    if b"AKIA" in raw:
        found += [(*m.span(), "access") for m in ACCESS.finditer(text) if m.end() - m.start() >= 18]
    if b"\1" * 16 in raw.translate(_HEX_RUN):
        found += [(*m.span(), "hex") for m in HEX.finditer(text)]
    return sorted(found, key=lambda s: (s[0], KINDS.index(s[2])))


class Novelty:
    def __init__(self, known: str = KNOWN):
        import zstandard

        self.pack = zstandard.ZstdCompressor(level=3, dict_data=zstandard.ZstdCompressionDict(known.encode(), dict_type=zstandard.DICT_TYPE_RAWCONTENT), write_content_size=False).compress

    def __call__(self, around: str, candidate: str) -> float:
        """Bytes that the candidate adds to its compressed surroundings, over its length."""
        head = around.encode()
        return (len(self.pack(head + candidate.encode())) - len(self.pack(head))) / len(candidate)


def novel_spans(text: str, lowered: bytes, base: list[tuple[int, int, str]], novelty: Novelty) -> list[tuple[int, int, str]]:
    if not any(w.encode() in lowered for w in SENSITIVE):
        return []
    out = []
    for m in LONG.finditer(text):
        a, b = m.span()
        s = m[0]
        mixed = sum((any("0" <= c <= "9" for c in s), any("a" <= c <= "z" for c in s), any("A" <= c <= "Z" for c in s)))
        if mixed < 2 or not any("0" <= c <= "9" for c in s) or any(a < y and x < b for x, y, _ in base):
            continue
        before = text[max(0, a - BEFORE) : a].lower()
        least = NOVEL if b - a <= SHORT else min(NOVEL, OF_BITS * math.log2(len(set(s))) / 8)
        if any(w in before for w in SENSITIVE) and novelty(text[max(0, a - AROUND) : a] + text[b : b + AROUND], s) >= least:
            out.append((a, b, "novel"))
    return out


def written(spans: list[tuple[int, int, str]]) -> str:
    return ",".join(f"{k}:{a}:{b}" for a, b, k in spans)


def find(docs: DataFrame) -> DataFrame:
    """doc_id, n_assign, n_access, n_hex, base_sha256, spans of every document."""
    made: list[Novelty] = []

    def run(batch: pa.RecordBatch) -> pa.RecordBatch:
        if not made:
            made.append(Novelty())
        rows = []
        for t in texts(batch):
            raw = t.encode()
            lowered = raw.lower()
            base = base_spans(t, raw, lowered)
            spans = sorted(base + novel_spans(t, lowered, base, made[0]), key=lambda s: (s[0], KINDS.index(s[2])))
            rows.append((*[sum(s[2] == k for s in base) for k in KINDS[:3]], hashlib.sha256(written(base).encode()).hexdigest(), written(spans)))
        arrays = [pa.array(x, t) for x, t in zip(zip(*rows, strict=True), [pa.int64()] * 3 + [pa.string()] * 2, strict=True)]
        return pa.RecordBatch.from_arrays([col(batch, "doc_id"), *arrays], names=["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return map_text(narrow(docs, "doc_id", "text"), run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string")
