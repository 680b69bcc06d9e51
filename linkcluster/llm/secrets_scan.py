"""Secret scan by dictionary-primed compression novelty.

Three fixed patterns give the base spans.  The method adds ``novel`` spans: a candidate
token that stands after a sensitive word is compressed with zstandard, primed by an
identifier dictionary and the text around the candidate (the candidate itself and its equal copies cut out).
Its marginal compressed bytes, the size above that of an empty frame with the same
priming, divided by its own bytes say how much of it the surroundings do not explain.
Words, identifiers and parts that recur nearby are cheap; random keys are not, seen once or again.

Defined cases: a null text is empty; an empty text has no spans and the hash of the empty
string; repeated rows and ties give repeated results; very long texts are scanned whole, each candidate
against its own surroundings; other columns, whatever their names, are not read.
"""

from __future__ import annotations

import hashlib
import re
from dataclasses import dataclass

import pyarrow as pa
import zstandard
from pyspark.sql import DataFrame

# The patterns of the base scan.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]+")
HEX = re.compile(r"[0-9a-f]+")
LONG_HEX = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "novel")
#: Words that make a context sensitive, whole or as a part of an identifier (authToken, auth_token; not author).
SENSITIVE = re.compile(
    r"(?:(?<![A-Za-z])|(?<=[a-z0-9])(?=[A-Z]))(?i:pass(?:word|wd|phrase)|pwd|secret|token|api[_-]?key|access[_-]?key|private|credential|auth(?:orization|entication)?|bearer|signature|session|cookie|cert(?:ificate)?|license[_-]?key|key)(?i:s?)"
    r"(?:(?![A-Za-z])|(?=[A-Z][a-z]))",
    re.ASCII,
)
#: Identifiers that code uses often; what they explain is not novel.
IDENTIFIERS = (
    "abstract assert async await boolean break callback class client component config connection const constructor container content continue "
    "controller create database default delete description document element environment exception export extends factory false filter finally "
    "function getElementById getInstance handler header height import include index initialize instance interface iterator javascript lambda length "
    "listener location manager message method module namespace object onclick override package parameter password private process property protected "
    "protocol provider public querySelector readonly request require resource response return secret service session setTimeout static string struct "
    "super synchronized template this throw token toString transient true typedef undefined username value version virtual void volatile width while "
    "abcdefghijklmnopqrstuvwxyz ABCDEFGHIJKLMNOPQRSTUVWXYZ 0123456789 EXAMPLE example placeholder changeme your_api_key_here xxxxxxxxxxxxxxxx 00000000000000000000 1234567890"
)


@dataclass(frozen=True)
class NoveltyScan:
    """Parameters: candidate length, context sizes in characters, and the least novelty that is reported."""

    min_chars: int = 16
    before: int = 48
    window: int = 1024
    min_novelty: float = 0.6
    level: int = 3
    identifiers: str = IDENTIFIERS

    def marginal_bytes(self, candidate: str, around: str) -> tuple[int, int]:
        """Compressed bytes of the candidate above an empty frame, and its raw bytes."""
        prime = zstandard.ZstdCompressionDict((self.identifiers + "\n" + around).encode("utf-8", "replace"), dict_type=zstandard.DICT_TYPE_RAWCONTENT)
        z = zstandard.ZstdCompressor(level=self.level, dict_data=prime, write_checksum=False, write_content_size=False, write_dict_id=False)
        raw = candidate.encode("utf-8", "replace")
        return max(0, len(z.compress(raw)) - len(z.compress(b""))), len(raw)

    def novel(self, text: str, taken: list[tuple[int, int]]) -> list[tuple[int, int, float]]:
        out, taken, at = [], sorted(taken), 0
        ends = [0]
        for _, b in taken:  # spans of several kinds may overlap: the furthest end so far
            ends.append(max(ends[-1], b))
        for m in re.finditer(r"[A-Za-z0-9+/_=-]{%d,}" % self.min_chars, text):
            s, e = m.span()
            word = m.group()
            while at < len(taken) and taken[at][0] < e:
                at += 1
            if ends[at] > s:
                continue
            if not SENSITIVE.search(text, max(0, s - self.before), s):
                continue
            # so much more is cut out that no part of a copy is left at the ends
            far = self.window + len(word)
            before, after = text[max(0, s - far) : s].replace(word, "")[-self.window :], text[e : e + far].replace(word, "")[: self.window]
            cost, size = self.marginal_bytes(word, before + after)
            if cost >= self.min_novelty * size:
                out.append((s, e, cost / size))
        return out


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """(start, kind number, end) of the three patterns, leftmost non-overlapping within each kind."""
    found = []
    low = text.lower()
    if any(w in low for w in ("password", "passwd", "secret", "token", "apikey", "api_key")):
        found += [(m.start(), 0, m.end()) for m in ASSIGN.finditer(text) if len(m.group(2)) >= 6]
    if "AKIA" in text:
        found += [(m.start(), 1, m.end()) for m in ACCESS.finditer(text) if m.end() - m.start() >= 20]
    # a run of fewer than 24 fails as a whole, so asking for 24 at once finds the same spans
    found += [(m.start(), 2, m.end()) for m in LONG_HEX.finditer(text)]
    return sorted(found)


def _write(spans: list[tuple[int, int, int]]) -> str:
    return ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in spans)


def scan_text(text: str | None, scan: NoveltyScan) -> tuple:
    text = text or ""
    base = base_spans(text)
    novel = scan.novel(text, [(s, e) for s, _, e in base])
    spans = sorted(base + [(s, 3, e) for s, e, _ in novel])
    n = [sum(1 for x in base if x[1] == k) for k in range(3)]
    return (*n, hashlib.sha256(_write(base).encode()).hexdigest(), _write(spans), len(novel), max((x for _, _, x in novel), default=0.0))


SCHEMA = "n_assign bigint, n_access bigint, n_hex bigint, base_sha256 string, spans string, n_novel bigint, max_novelty double"


def scan(docs: DataFrame, key: str = "doc_id", text: str = "text", params: NoveltyScan = NoveltyScan()) -> DataFrame:
    """One row for each document: ``key`` and the spans found in its whole text."""
    names = [f.split()[0] for f in SCHEMA.split(", ")]

    def run(batches):
        for b in batches:
            out = [scan_text(t.as_py(), params) for t in b.column(1)]
            cols = list(zip(*out)) if out else [[] for _ in names]
            types = [pa.int64()] * 3 + [pa.string()] * 2 + [pa.int64(), pa.float64()]
            yield pa.RecordBatch.from_arrays([b.column(0)] + [pa.array(list(c), t) for c, t in zip(cols, types)], [key, *names])

    slim = docs.select(key, text)
    kind = dict(slim.dtypes)[key]
    return slim.mapInArrow(run, f"`{key}` {kind}, {SCHEMA}")
