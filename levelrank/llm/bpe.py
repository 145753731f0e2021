"""Byte-level BPE with the tokenizers library over Arrow batches.

A text's tokens come from pieces that the pattern cuts independently of each other. A
single blank between two visible characters always starts a piece and a single newline
between two visible characters is one, so the texts are cut there, each distinct piece is
encoded once by the library, and a text's ids are the joined bytes of its pieces' ids. Texts
in which blanks or newlines come in runs, or next to other white space, leave odd pieces
when cut and go to the library whole.
"""

from __future__ import annotations

import base64
import hashlib
import json
import os
import re
import string
from collections.abc import Iterator

import numpy as np
import public_tokenizers
import pyarrow as pa
import pyarrow.compute as pc
from pyspark.sql import DataFrame

from levelrank.llm.common import arrow_rows

JSON_FILE, RANK_FILE = "byte_bpe_50k.json", "byte_bpe_50k.tiktoken"
#: Pieces, and bytes of them and their ids, that a worker process remembers from one task to the next.
REMEMBERED, REMEMBERED_BYTES = 1_000_000, 200_000_000
#: Bytes of text that are cut into pieces at a time.
BLOCK_BYTES = 16_000_000
_WORKER: dict[str, Pieces] = {}
#: Characters that some pattern engines take for white space and Python does not.
DOUBTFUL = re.compile("[\\u180e\\u200b\\ufeff]")


def odd_pieces(pieces: list[str]) -> set[str]:
    """Pieces that are empty but for their blank, or hold white space beyond it."""
    bare = [p[1:] if p[:1] == " " else p for p in pieces]
    joined = " ".join(bare)
    if joined.split() == bare and not DOUBTFUL.search(joined):
        return set()
    return {p for p, b in zip(pieces, bare) if b.split() != [b] or DOUBTFUL.search(b)}


def byte_characters() -> list[str]:
    """The character that stands for each byte in byte-level vocabularies: printable
    Latin-1 bytes for themselves, the others counted up from 256."""
    plain = [*range(33, 127), *range(161, 173), *range(174, 256)]
    table = {b: chr(b) for b in plain}
    for k, b in enumerate(x for x in range(256) if x not in table):
        table[b] = chr(256 + k)
    return [table[b] for b in range(256)]


def json_of_file(path: str) -> str:
    with open(path, encoding="utf-8") as f:
        return f.read()


def json_of_ranks(path: str) -> str:
    """A tokenizer of the library from a rank file: each token's last merge is the pair
    that merging by lower ranks leaves."""
    with open(path, "rb") as f:
        ranks = {base64.b64decode(a): int(b) for a, b in map(bytes.split, f)}
    chars = byte_characters()
    name = lambda token: "".join(chars[b] for b in token)
    merges = []
    for token, rank in sorted(ranks.items(), key=lambda x: x[1]):
        if len(token) > 1:
            parts = [token[i : i + 1] for i in range(len(token))]
            while len(parts) > 2:
                best = min(range(len(parts) - 1), key=lambda i: ranks.get(parts[i] + parts[i + 1], 1 << 60))
                if ranks.get(parts[best] + parts[best + 1], 1 << 60) >= rank:
                    break
                parts[best : best + 2] = [parts[best] + parts[best + 1]]
            if len(parts) == 2:
                merges.append([name(parts[0]), name(parts[1])])
    level = {"type": "ByteLevel", "add_prefix_space": False, "trim_offsets": True, "use_regex": True}
    model = {"type": "BPE", "dropout": None, "unk_token": None, "continuing_subword_prefix": "", "end_of_word_suffix": "", "fuse_unk": False, "byte_fallback": False, "ignore_merges": False, "vocab": {name(t): r for t, r in ranks.items()}, "merges": merges}
    return json.dumps({"version": "1.0", "truncation": None, "padding": None, "added_tokens": [], "normalizer": None, "pre_tokenizer": level, "post_processor": None, "decoder": level, "model": model})


class Pieces:
    """Encodes texts to id bytes (little-endian unsigned 32-bit), remembering pieces."""

    def __init__(self, spec: str):
        os.environ["TOKENIZERS_PARALLELISM"] = "false"
        from tokenizers import Tokenizer

        self.tokenizer = Tokenizer.from_str(spec)
        self.tokenizer.encode_special_tokens = True  # their names in a text are ordinary text
        self.fixed = {"\n": self._library(["\n"])[0]}
        self.forget()

    def forget(self) -> None:
        """Known pieces and their ids, row by row, in Arrow arrays: looked up a whole batch at a time."""
        self.known = pa.array(list(self.fixed), pa.large_string())
        self.ids = pa.array(list(self.fixed.values()), pa.large_binary())

    def _library(self, bodies: list[str]) -> list[bytes]:
        return [np.array(e.ids, "<u4").tobytes() for e in self.tokenizer.encode_batch_fast(bodies, add_special_tokens=False)]

    def _learn(self, pieces: list[str]) -> list[bytes]:
        """Encode many pieces as one text with a newline before each: it is a token by itself
        there, and no piece holds one, so it marks where a piece's tokens begin."""
        mark, out = np.frombuffer(self.fixed["\n"], "<u4")[0], []
        for k in range(0, len(pieces), 4_000):
            raw = self._library(["\n" + "\n".join(pieces[k : k + 4_000])])[0]
            at = 4 * np.flatnonzero(np.frombuffer(raw, "<u4") == mark)
            out += [raw[i:j] for i, j in zip((at + 4).tolist(), [*at[1:].tolist(), len(raw)])]
        return out

    def _learn_all(self, missing: list[str]) -> None:
        """Punctuation after a letter or digit, up to a piece's end, is a match of its own: a word
        and its tail are learned apart and put together."""
        tails, bare, ends = [], set(), set()
        for p in missing:
            word = p.rstrip(string.punctuation)
            if len(word) < len(p) and word[-1:].isalnum():
                tails.append((p, word, p[len(word) :]))
            else:
                bare.add(p)
        for _, word, tail in tails:
            ends.add(word)
            ends.add(tail)
        ends = list(ends - bare)
        at = pc.index_in(pa.array(ends, pa.large_string()), self.known)
        got = dict(zip(ends, self.ids.take(at).to_pylist()))
        fresh = [*bare, *(p for p in ends if got[p] is None)]
        got.update(zip(fresh, self._learn(fresh)))
        fresh += [p for p, _, _ in tails]
        raw = [got[p] for p in fresh[: len(fresh) - len(tails)]] + [got[word] + got[tail] for _, word, tail in tails]
        self.known = pa.concat_arrays([self.known, pa.array(fresh, pa.large_string())])
        self.ids = pa.concat_arrays([self.ids, pa.array(raw, pa.large_binary())])

    def batch(self, bodies: pa.Array) -> list[memoryview | bytes]:
        """Id bytes of each text (no nulls). Arrow cuts the texts, numbers their distinct pieces and
        gathers the pieces' ids; Python sees the pieces not known yet."""
        if len(self.known) > REMEMBERED or self.known.nbytes + self.ids.nbytes > REMEMBERED_BYTES:
            self.forget()
        bodies = bodies.cast(pa.large_string())
        marked = pc.replace_substring(pc.replace_substring(bodies, "\n", "\0\n\0"), " ", "\0 ")
        cut = pc.split_pattern(marked, "\0")
        at = cut.offsets.to_numpy()
        coded = cut.values.slice(at[0], at[-1] - at[0]).dictionary_encode()
        at = at - at[0]
        distinct = coded.dictionary
        found = pc.index_in(distinct, self.known)
        new = distinct.filter(found.is_null()).to_pylist()
        odd = odd_pieces(new)
        if len(new) > len(odd):
            before, gaps = len(self.known), found.is_null()
            self._learn_all([p for p in new if p not in odd] if odd else new)
            learned = pc.index_in(distinct.filter(gaps), self.known.slice(before))
            found = pc.replace_with_mask(found, gaps, pc.add(learned, pa.scalar(before, pa.int32())))
        ids = self.ids.take(found).fill_null(b"").take(coded.indices)
        ends = np.frombuffer(ids.buffers()[1], np.int64, len(ids) + 1, 8 * ids.offset)
        raw = memoryview(ids.buffers()[2] or b"")
        bounds = ends[at].tolist()
        out: list[memoryview | bytes] = [raw[i:j] for i, j in zip(bounds, bounds[1:])]
        for k, body in self._whole(bodies, at, coded.indices.to_numpy(), distinct, odd).items():
            out[k] = body
        return out

    def _whole(self, bodies: pa.Array, at: np.ndarray, index: np.ndarray, distinct: pa.Array, odd: set[str]) -> dict[int, bytes]:
        """Id bytes of the texts that hold an odd piece or the mark itself, by the library. The empty
        piece at the end of a text, which is empty or ends with a newline, is none."""
        taken = pc.match_substring(bodies, "\0").to_numpy(zero_copy_only=False)
        if odd:
            strange = pc.is_in(distinct, pa.array(list(odd), pa.large_string())).to_numpy(zero_copy_only=False)
            hit = strange[index]
            if "" in odd:
                last = at[1:] - 1
                hit[last[index[last] == pc.index(distinct, "").as_py()]] = False
            before = np.concatenate([[0], np.cumsum(hit)])
            taken = taken | (before[at[1:]] > before[at[:-1]])
        rows = np.flatnonzero(taken)
        return dict(zip(rows.tolist(), self._library(bodies.take(pa.array(rows)).to_pylist())))


def pieces_of(spec: str) -> Pieces:
    """The worker's encoder for a tokenizer; Spark reuses worker processes, so what one task
    has learned serves the next."""
    key = hashlib.sha256(spec.encode()).hexdigest()
    if key not in _WORKER:
        _WORKER.clear()
        _WORKER[key] = Pieces(spec)
    return _WORKER[key]


def blocks(batch: pa.RecordBatch, size: int = BLOCK_BYTES) -> Iterator[tuple[int, int, pa.Array]]:
    """(start, end, texts) of slices of about so many bytes, null as the empty text; very long
    texts go alone."""
    bodies = batch.column("text").fill_null("")
    start = held = 0
    for i, n in enumerate(pc.binary_length(bodies).to_pylist()):
        held += n
        if held >= size:
            yield start, i + 1, bodies.slice(start, i + 1 - start)
            start, held = i + 1, 0
    if start < len(bodies):
        yield start, len(bodies), bodies.slice(start)


class Bytes:
    """Decoding: ids back to bytes through the reversed byte table, so characters that
    several tokens share come back whole."""

    def __init__(self, spec: str):
        model = json.loads(spec)
        back = {c: b for b, c in enumerate(byte_characters())}
        vocab = dict(model["model"]["vocab"])
        special = {t["content"]: t["id"] for t in model.get("added_tokens") or []}
        self.table: list[bytes] = [b""] * (max([*vocab.values(), *special.values()]) + 1)
        for token, i in vocab.items():
            self.table[i] = bytes(back[c] for c in token) if all(c in back for c in token) else token.encode()
        for token, i in special.items():
            self.table[i] = token.encode()
        self.names = [str(i) for i in range(len(self.table))]
        self.lengths = np.array([len(t) for t in self.table])

    def decode(self, ids: list[int]) -> bytes:
        return b"".join(map(self.table.__getitem__, ids))

    def listed(self, ids: list[int]) -> str:
        return " ".join(map(self.names.__getitem__, ids))


    def offsets(self, ids: np.ndarray, body: bytes) -> np.ndarray:
        """(start, end) of each token in characters of the text whose UTF-8 bytes are ``body``; a token that holds
        a part of a character names the whole of it."""
        ends = np.cumsum(self.lengths[ids])
        character = np.cumsum(np.frombuffer(body, np.uint8) & 0xC0 != 0x80)  # of each byte, from 1
        return np.stack([character[ends - self.lengths[ids]] - 1, character[ends - 1]], axis=1)


def encode_with_offsets(spec: str, text: str) -> list[tuple[int, int, int]]:
    """(id, start, end) per token, in characters of the text."""
    table, body = Bytes(spec), pa.array([text], pa.string())
    ids = np.frombuffer(pieces_of(spec).batch(body)[0], "<u4")
    return [(int(i), int(a), int(b)) for i, (a, b) in zip(ids, table.offsets(ids, text.encode()))]


def round_trip(docs: DataFrame, spec: str | None = None) -> DataFrame:
    """doc_id, n_tokens, ids_sha256, decoded_sha256, and offsets_sha256: of the tokens' starts and ends in
    characters, in turn, as little-endian 32-bit integers. Null texts count as empty: no tokens."""
    spec = spec or json_of_ranks(public_tokenizers.path(RANK_FILE))
    shared = docs.sparkSession.sparkContext.broadcast(spec)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces, table = pieces_of(shared.value), Bytes(shared.value)
        for b in batches:
            ids = b.column("doc_id")
            for start, end, body in blocks(b):
                rows = [], [], [], []
                for raw in pieces.batch(body):
                    coded = np.frombuffer(raw, "<u4")
                    got = coded.tolist()
                    decoded = table.decode(got)
                    rows[0].append(len(got))
                    rows[1].append(hashlib.sha256(table.listed(got).encode()).hexdigest())
                    rows[2].append(hashlib.sha256(decoded).hexdigest())
                    rows[3].append(hashlib.sha256(table.offsets(coded, decoded).astype("<i4").tobytes()).hexdigest())
                yield pa.record_batch([ids[start:end], pa.array(rows[0], pa.int64()), *(pa.array(r, pa.string()) for r in rows[1:])], ["doc_id", "n_tokens", "ids_sha256", "decoded_sha256", "offsets_sha256"])

    return arrow_rows(docs, ["doc_id", "text"], run, "doc_id long, n_tokens long, ids_sha256 string, decoded_sha256 string, offsets_sha256 string", BLOCK_BYTES)


def encoded(docs: DataFrame, spec: str | None = None) -> DataFrame:
    """doc_id, token ids, and the text decoded from them: the last stage of the pipeline."""
    spec = spec or json_of_ranks(public_tokenizers.path(RANK_FILE))
    shared = docs.sparkSession.sparkContext.broadcast(spec)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        pieces, table = pieces_of(shared.value), Bytes(shared.value)
        for b in batches:
            ids = b.column("doc_id")
            for start, end, body in blocks(b):
                got = [np.frombuffer(raw, "<u4").astype(np.int32) for raw in pieces.batch(body)]
                ends = np.cumsum([0, *map(len, got)]).astype(np.int32)
                lists = pa.ListArray.from_arrays(pa.array(ends), pa.array(np.concatenate(got)))
                same = [hashlib.sha256(table.decode(x.tolist())).hexdigest() for x in got]
                yield pa.record_batch([ids[start:end], pa.array(np.diff(ends).astype(np.int64)), lists, pa.array(same, pa.string())], ["doc_id", "n_tokens", "ids", "decoded_sha256"])

    return arrow_rows(docs, ["doc_id", "text"], run, "doc_id long, n_tokens long, ids array<int>, decoded_sha256 string", BLOCK_BYTES)
