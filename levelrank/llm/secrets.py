"""Secret scans: base patterns and a linear-chain conditional random field.

The field tags every token of every text as begin, inside or outside of a secret, from token
shape, length, spread of characters, neighbouring words and facts about the file, and Viterbi
picks the best tags. It is fitted on a bounded sample of stretches of all texts: the ``SAMPLE``
first in hash order with a value that the base patterns find, their label, and the ``SAMPLE``
first without. Half of those without get one planted secret of a kind that the base patterns
do not know (``CUES``, ``ALPHABETS``), a quarter a planted harmless value, so the field learns
shapes and neighbourhoods instead of the patterns. Its spans are added where no base span is.

Null and empty texts have no spans; repeated rows are reported one by one; very long texts are
tagged whole, in a few array operations; columns other than doc_id and text are not read.
"""

from __future__ import annotations

import hashlib
import re
import string
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import xxhash
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.llm.common import arrow_rows, texts
from levelrank.plans.staging import materialise

#: The base patterns; lengths are part of the patterns where runs are whole.
ASSIGN = re.compile(r"""(password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", re.IGNORECASE | re.ASCII)
ACCESS = re.compile(r"AKIA[A-Z0-9]{16,}")
HEXES = re.compile(r"[0-9a-f]{24,}")
KINDS = ("assign", "access", "hex", "secret")
WORDS = ("password", "passwd", "secret", "token", "api_key", "apikey")

#: Words before planted secrets, and the characters that planted values are drawn from.
CUES = ("passphrase is ", "the pwd is ", "pwd=", "Authorization: Bearer ", "private key ", "credentials: ", "client_key = ", "login with ", "auth ", "access code ", "signing key: ", "passcode ", "-u admin -p ", "pass: ", "apitoken ", "credential ")
ALPHABETS = (string.ascii_letters + string.digits, string.ascii_letters, string.ascii_letters + string.digits + "+/", string.ascii_uppercase + string.digits, "0123456789ABCDEF", string.ascii_letters + string.digits + "_-")
PREFIXES = ("", "", "", "ghp_", "sk_live_", "xoxb-", "eyJ")
#: Words before harmless values.
HARMLESS = ("on page ", "order ", "call ", "see ", "at ", "version ", "in ", "from ", "mail ", "by ", "the number ", "host ")

STRETCH = re.compile(r"\S.{0,200}\S*", re.DOTALL)
TOKEN = re.compile(r"[\w+/=-]+|[^\s\w]")
BITS, SAMPLE, EPOCHS, UPDATES = 16, 1200, 6, 6000
BEGIN, INSIDE, OUTSIDE = 0, 1, 2
NEVER = -1e3
#: Bytes of text that are tagged at a time.
SLICE = 6_000_000


def base_spans(text: str) -> list[tuple[int, int, int, int]]:
    """(start, kind, end, start of the value), by start, then kind."""
    out = []
    low = text.lower()
    if any(w in low for w in WORDS):
        out += [(m.start(), 0, m.end(), m.start(2)) for m in ASSIGN.finditer(text) if m.end(2) - m.start(2) >= 6]
    if "AKIA" in text:
        out += [(m.start(), 1, m.end(), m.start()) for m in ACCESS.finditer(text)]
    out += [(m.start(), 2, m.end(), m.start()) for m in HEXES.finditer(text)]
    return sorted(out)


def stretches(text: str) -> list[tuple[int, int]]:
    """The whole text in stretches of about 200 characters, cut at white space."""
    return [m.span() for m in STRETCH.finditer(text)]


# ---------------------------------------------------------------- features
#: Columns of ``columns``: the token's own, one per kind of file, and what it gives the tokens
#: one, two and three after it and the one before.
OWN, FILES, NEAR = 6, 4, 4
EDGE = np.uint64(0x5851F42D4C957F2D)


def _bucket(x: np.ndarray, salt: int) -> np.ndarray:
    h = (x.astype(np.uint64) ^ np.uint64(salt * 0x9E3779B97F4A7C15 & 0xFFFFFFFFFFFFFFFF)) * np.uint64(0xD6E8FEB86659FD93)
    h ^= h >> np.uint64(32)
    return ((h * np.uint64(0xD6E8FEB86659FD93)) >> np.uint64(64 - BITS)).astype(np.int64)


def _named(values: pa.Array) -> np.ndarray:
    return pd.util.hash_array(values.to_numpy(zero_copy_only=False).astype(object), categorize=False)


def columns(tokens: pa.Array) -> np.ndarray:
    """(n, OWN + FILES + NEAR) feature buckets of tokens, by array operations."""
    n = pc.utf8_length(tokens).to_numpy(zero_copy_only=False).astype(np.int64)
    short = n < 17
    low = np.where(short, _named(pc.utf8_lower(tokens)), np.uint64(1))
    shape = tokens
    for pattern, mark in (("[0-9]+", "0"), (r"\p{Lu}+", "A"), (r"\p{Ll}+", "a")):
        shape = pc.replace_substring_regex(shape, pattern, mark)
    shape = np.where(pc.utf8_length(shape).to_numpy(zero_copy_only=False) < 12, _named(shape), np.uint64(2))
    size = np.minimum(n // 4, 12)
    spread = np.fromiter((len(set(t)) for t in tokens.to_pylist()), np.int64, len(tokens)) // 2
    pair = lambda a, b: a.astype(np.uint64) * np.uint64(1000003) + b.astype(np.uint64)
    own = [_bucket(shape, 1), _bucket(size, 2), _bucket(spread, 3), _bucket(np.where(n < 12, low, np.uint64(3)), 4), _bucket(pair(shape, size), 5), _bucket(pair(size, spread), 6)]
    return np.stack([*own, *(_bucket(size, 10 + k) for k in range(FILES)), *(_bucket(low, 20 + k) for k in range(NEAR))], axis=1)


def edge_buckets() -> np.ndarray:
    """Buckets that stand for the neighbours past either end."""
    return np.array([_bucket(np.array([EDGE]), 20 + k)[0] for k in range(NEAR)])


def file_fact(text: str) -> int:
    """Whether the text looks like code or settings: 0 to 3."""
    return 2 * int(text.count("=") * 200 > len(text)) + int(text.count("{") * 500 > len(text))


def features(tokens: list[str], file: int) -> np.ndarray:
    """(n, OWN + 1 + NEAR) buckets that are on at each token of one stretch."""
    cols, edge = columns(pa.array(tokens, pa.string())), edge_buckets()
    near = np.empty((len(tokens), NEAR), np.int64)
    for k in range(NEAR):
        ahead, at = k == NEAR - 1, min(k + 1, len(tokens))
        given = cols[:, OWN + FILES + k]
        near[:, k] = np.r_[given[1:], edge[k]] if ahead else np.r_[np.full(at, edge[k]), given[: len(tokens) - at]]
    return np.concatenate([cols[:, :OWN], cols[:, OWN + file : OWN + file + 1], near], axis=1)


# ---------------------------------------------------------------- the field
class Field:
    """Weights by hashed feature and tag, and tag transitions."""

    def __init__(self):
        self.emit = np.zeros((1 << BITS, 3))
        self.move = np.zeros((3, 3))
        self.move[OUTSIDE, INSIDE] = NEVER  # a secret begins with its begin tag

    def scores(self, feats: np.ndarray) -> np.ndarray:
        return self.emit[feats].sum(axis=1)

    def best(self, e: np.ndarray, after_outside: bool = False, before_outside: bool = False) -> list[int]:
        """The best tags for one row of tag scores per token, by Viterbi; optionally between outside tags."""
        rows = e.tolist()
        (bb, bi, bo), (ib, ii, io), (ob, oi, oo) = self.move.tolist()
        b, i, o = rows[0]
        i += NEVER
        if after_outside:
            b, o = b + ob, o + oo
        back = []
        for x, y, z in rows[1:]:
            nb, kb = b + bb, 0
            if (v := i + ib) > nb:
                nb, kb = v, 1
            if (v := o + ob) > nb:
                nb, kb = v, 2
            ni, ki = b + bi, 0
            if (v := i + ii) > ni:
                ni, ki = v, 1
            if (v := o + oi) > ni:
                ni, ki = v, 2
            no, ko = b + bo, 0
            if (v := i + io) > no:
                no, ko = v, 1
            if (v := o + oo) > no:
                no, ko = v, 2
            b, i, o = nb + x, ni + y, no + z
            back.append((kb, ki, ko))
        last = (b + bo, i + io, o + oo) if before_outside else (b, i, o)
        tag = last.index(max(last))
        tags = [tag]
        for k in reversed(back):
            tag = k[tag]
            tags.append(tag)
        return tags[::-1]

    def tagged(self, e: np.ndarray, ends: np.ndarray) -> np.ndarray:
        """Best tags of many texts at once; ``ends`` are the texts' ends in ``e``.

        A token is outside on every best path if that beats its other tags by more than all
        transitions could make up for, the next token's change from inside to begin included. Viterbi
        runs on the stretches between such tokens."""
        tags = np.full(len(e), OUTSIDE, np.int8)
        if not len(e):
            return tags
        free = np.delete(self.move.ravel(), OUTSIDE * 3 + INSIDE)
        slack = 3 * (free.max() - free.min())
        first = np.zeros(len(e), bool)
        first[np.r_[0, ends[:-1]][np.r_[0, ends[:-1]] < ends]] = True
        last = np.zeros(len(e), bool)
        last[ends[ends > np.r_[0, ends[:-1]]] - 1] = True
        redo = np.r_[np.maximum(0, e[1:, INSIDE] - e[1:, BEGIN]), 0.0]
        redo[last] = 0
        open_ = e[:, OUTSIDE] - np.maximum(e[:, BEGIN], e[:, INSIDE]) - redo <= slack
        starts = np.flatnonzero(open_ & (first | ~np.r_[False, open_[:-1]]))
        stops = np.flatnonzero(open_ & (last | ~np.r_[open_[1:], False])) + 1
        alone = (stops - starts == 1) & ~first[starts] & ~last[stops - 1]
        one = starts[alone]
        (_, _, bo), _, (ob, _, oo) = self.move.tolist()
        tags[one[e[one, BEGIN] + ob + bo > e[one, OUTSIDE] + 2 * oo]] = BEGIN
        for a, z in zip(starts[~alone].tolist(), stops[~alone].tolist()):
            tags[a:z] = self.best(e[a:z], not first[a], not last[z - 1])
        return tags

    def marginals(self, e: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
        """Expected tags and transitions by the forward-backward recursions, scaled per step."""
        n, m = len(e), np.exp(self.move)
        p = np.exp(e - e.max(axis=1, keepdims=True))
        a, b = np.empty((n, 3)), np.ones((n, 3))
        p[0, INSIDE] = 0
        a[0] = p[0] / p[0].sum()
        for t in range(1, n):
            x = (a[t - 1] @ m) * p[t]
            a[t] = x / x.sum()
        pairs = np.zeros((3, 3))
        for t in range(n - 2, -1, -1):
            x = m @ (p[t + 1] * b[t + 1])
            b[t] = x / x.sum()
            y = a[t][:, None] * m * (p[t + 1] * b[t + 1])
            pairs += y / y.sum()
        g = a * b
        return g / g.sum(axis=1, keepdims=True), pairs

    def fit(self, data: list[tuple[np.ndarray, list[int]]], rate: float = 0.3, decay: float = 1e-4) -> Field:
        square = np.full_like(self.emit, 1e-6)
        for _ in range(max(EPOCHS, min(60, UPDATES // max(1, len(data))))):
            for f, tags in data:
                p, pairs = self.marginals(self.emit[f].sum(axis=1))
                gold = np.eye(3)[tags]
                grad = np.repeat(gold - p, f.shape[1], axis=0)
                at = f.ravel()
                np.add.at(square, at, grad**2)
                np.add.at(self.emit, at, rate * grad / np.sqrt(square[at]) - decay * self.emit[at])
                seen = np.zeros((3, 3))
                np.add.at(seen, (tags[:-1], tags[1:]), 1)
                step = 0.05 * (seen - pairs) / max(1, len(tags))
                step[OUTSIDE, INSIDE] = 0
                self.move += step
        return self

    def table(self, tokens: pa.Array) -> np.ndarray:
        """(n, FILES + NEAR, 3) summed weights per token: itself in each kind of file, then its gifts to its neighbours."""
        cols = columns(tokens)
        own = self.emit[cols[:, :OWN]].sum(axis=1)
        out = self.emit[cols[:, OWN:]].astype(np.float32)
        out[:, :FILES] += own[:, None, :]
        return out

    def of_texts(self, bodies: list[str]) -> tuple[np.ndarray, np.ndarray]:
        """(tags of all tokens, ends of the texts in them); scores are those of ``features`` over each whole text."""
        found = [TOKEN.findall(t) for t in bodies]
        ends = np.cumsum([len(x) for x in found])
        coded = pa.array([t for x in found for t in x], pa.large_string()).dictionary_encode()
        if not len(coded):
            return np.zeros(0, np.int8), ends
        table, at = self.table(coded.dictionary), coded.indices.to_numpy()
        sizes = np.array([len(x) for x in found])
        e = table[at, np.repeat([file_fact(t) for t in bodies], sizes)]
        begins, edge = (ends - sizes)[sizes > 0], self.emit[edge_buckets()]
        last = ends[sizes > 0] - 1
        for k in range(NEAR):
            given = table[:, FILES + k][at]
            if k == NEAR - 1:
                given = np.concatenate([given[1:], given[:1]])
                given[last] = edge[k]
            else:
                given = np.concatenate([given[-k - 1 :], given[: -k - 1]])[: len(at)] if len(at) > k else given
                for j in range(k + 1):
                    given[np.minimum(begins + j, last)[begins + j <= last]] = edge[k]
            e += given
        return self.tagged(e, ends), ends


# ---------------------------------------------------------------- training
def _labels(spans: list[tuple[int, int]], secret: list[tuple[int, int]]) -> list[int]:
    tags = [OUTSIDE] * len(spans)
    for value, end in secret:
        inside = [i for i, (a, b) in enumerate(spans) if a < end and b > value]
        for k, i in enumerate(inside):
            tags[i] = BEGIN if k == 0 else INSIDE
    return tags


def _value(rng: np.random.Generator, alphabet: str, low: int, high: int) -> str:
    return "".join(rng.choice(list(alphabet), int(rng.integers(low, high))))


def _harmless(rng: np.random.Generator) -> str:
    n = lambda a, b: str(rng.integers(a, b))
    made = (n(1, 10**9), f"{n(0, 256)}.{n(0, 256)}.{n(0, 256)}.{n(0, 256)}", f"name.{n(1, 99)}@mail{n(0, 9)}.example.com", f"+1 ({n(100, 999)}) 555-{n(1000, 9999)}", f"2{n(100, 999)}-0{n(1, 9)}-1{n(0, 9)}", f"https://www.example.com/{n(1, 9999)}/page", f"{n(10**15, 10**16)}", f"v{n(1, 9)}.{n(0, 99)}.{n(0, 99)}", "WITHOUT", "Mc" + "Word" * int(rng.integers(1, 3)), "well-known-word")
    return made[rng.integers(len(made))]


def planted(body: str, h: int) -> tuple[str, list[tuple[int, int]]]:
    """A stretch with a planted secret (by its hash: half of them), a harmless value (a quarter) or nothing, and the secret's place."""
    rng = np.random.default_rng(h)
    words, kind = body.split(" "), h % 4
    if kind == 3:
        return body, []
    at = int(rng.integers(0, len(words) + 1))
    if kind == 2:
        return " ".join([*words[:at], HARMLESS[rng.integers(len(HARMLESS))] + _harmless(rng), *words[at:]]), []
    cue = CUES[rng.integers(len(CUES))]
    value = PREFIXES[rng.integers(len(PREFIXES))] + _value(rng, ALPHABETS[rng.integers(len(ALPHABETS))], 10, 45)
    if rng.random() < 0.25:
        value = _value(rng, string.ascii_lowercase, 4, 9).capitalize() + _value(rng, string.digits, 1, 5) + _value(rng, "!_-=+", 0, 2)
    quote = '"' if rng.random() < 0.2 else ""
    before = " ".join([*words[:at], cue]) + quote
    return before + value + quote + " " + " ".join(words[at:]), [(len(before), len(before) + len(value))]


def sample_of(docs: DataFrame, sample: int = SAMPLE) -> list:
    """Rows (kind, h, body, file, secret) of the ``sample`` stretches with a base value (kind 0) and as many without that come first in hash order over all texts; each once."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held: tuple[dict, dict] = ({}, {})
        upto = [1 << 63, 1 << 63]  # no stretch past the sample can come first
        for b in batches:
            for t in texts(b):
                base, file = base_spans(t), None
                for a, z in stretches(t):
                    own = [(max(v, a) - a, min(e, z) - a) for _, _, e, v in base if e > a and v < z] if base else []
                    kind, body = int(not own), t[a:z]
                    h = xxhash.xxh64_intdigest(body.encode("utf-8", "surrogatepass"), 1) >> 1
                    if h >= upto[kind] or h in held[kind]:
                        continue
                    file = file_fact(t) if file is None else file
                    held[kind][h] = (body, file, own)
                    if len(held[kind]) > 2 * sample:
                        first = sorted(held[kind])
                        upto[kind] = first[sample]
                        for h in first[sample:]:
                            del held[kind][h]
        for kind in (0, 1):
            rows = [(h, *held[kind][h]) for h in sorted(held[kind])[:sample]]
            yield pa.record_batch([pa.array([kind] * len(rows), pa.int32()), pa.array([r[0] for r in rows], pa.int64()), pa.array([r[1] for r in rows], pa.string()), pa.array([r[2] for r in rows], pa.int32()), pa.array([[x for s in r[3] for x in s] for r in rows], pa.list_(pa.int32()))], ["kind", "h", "body", "file", "secret"])

    found = arrow_rows(docs, ["text"], run, "kind int, h long, body string, file int, secret array<int>")
    once = materialise(found.groupBy("kind", "h").agg(F.min(F.struct("body", "file", "secret")).alias("row")).select("kind", "h", "row.*"), "stretches")
    return [r for kind in (0, 1) for r in once.where(F.col("kind") == kind).orderBy("h").limit(sample).collect()]


def train(docs: DataFrame, sample: int = SAMPLE) -> Field:
    """The field, fitted on ``sample_of`` with planted values."""
    data = []
    for r in sorted(sample_of(docs, sample), key=lambda r: r.h):
        body, secret = (r.body, list(zip(r.secret[::2], r.secret[1::2]))) if not r.kind else planted(r.body, r.h)
        spans = [m.span() for m in TOKEN.finditer(body)]
        if len(spans) > 1:
            data.append((features([body[a:b] for a, b in spans], r.file), _labels(spans, secret)))
    return Field().fit(data)


# ---------------------------------------------------------------- reports
def added_spans(text: str, tags: np.ndarray, base: list[tuple[int, int, int]]) -> list[tuple[int, int, int]]:
    """Spans of tagged tokens of six or more characters that meet no base span, as (start, kind, end)."""
    if not (tags != OUTSIDE).any():
        return []
    out: list[tuple[int, int, int]] = []
    run: list[int] | None = None
    for m, tag in zip(TOKEN.finditer(text), tags.tolist()):
        if run and tag != INSIDE:
            out.append((run[0], 3, run[1]))
            run = None
        if tag == BEGIN:
            run = [*m.span()]
        elif tag == INSIDE and run:
            run[1] = m.end()
    if run:
        out.append((run[0], 3, run[1]))
    return [x for x in out if x[2] - x[0] >= 6 and not any(s < x[2] and x[0] < e for s, _, e in base)]


def all_spans(bodies: list[str], field: Field) -> list[tuple[list[tuple[int, int, int]], list[tuple[int, int, int]]]]:
    """Base spans and those the field adds, per text, as (start, kind, end)."""
    tags, ends = field.of_texts(bodies)
    out = []
    for t, a, z in zip(bodies, np.r_[0, ends[:-1]].tolist() if len(ends) else [], ends.tolist()):
        base = [(s, k, e) for s, k, e, _ in base_spans(t)]
        out.append((base, added_spans(t, tags[a:z], base)))
    return out


def report(docs: DataFrame, field: Field | None = None) -> DataFrame:
    """One row per row of ``docs``; null or empty texts have no spans."""
    shared = docs.sparkSession.sparkContext.broadcast(field or train(docs))
    said = lambda rows: ",".join(f"{KINDS[k]}:{s}:{e}" for s, k, e in sorted(rows))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for b in batches:
            out = []
            for base, added in all_spans(texts(b), shared.value):
                kinds = [k for _, k, _ in base]
                out.append((*(kinds.count(k) for k in range(3)), hashlib.sha256(said(base).encode()).hexdigest(), said(base + added)))
            ints = [pa.array([r[c] for r in out], pa.int64()) for c in range(3)]
            yield pa.record_batch([b.column("doc_id"), *ints, *(pa.array([r[c] for r in out], pa.string()) for c in (3, 4))], ["doc_id", "n_assign", "n_access", "n_hex", "base_sha256", "spans"])

    return arrow_rows(docs.withColumn("doc_id", F.col("doc_id").cast("long")), ["doc_id", "text"], run, "doc_id long, n_assign long, n_access long, n_hex long, base_sha256 string, spans string", SLICE)
