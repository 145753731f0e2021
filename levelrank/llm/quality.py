"""Quality rules: text statistics and n-gram perplexity bands.

The language model is a modified Kneser-Ney bigram model per language over every word and every
bigram of every document: no vocabulary, no counts and no languages are cut. It lives in sorted hash arrays,
dealt out by ranges of the hash, and never meets the driver or a broadcast:

1. texts become streams: per batch of texts the sorted array of its words' hashes (language and word) and
   the texts as places in it. The stream table is bucketed by batch, so later steps find it in place;
2. each batch sends the sorted array of its bigrams' hashes and counts, cut into hash ranges. A range's task
   merges the arrays it gets into the model's array of that range and answers each with the counts of
   its bigrams in all documents, and which of them it owns (a bigram's first batch does);
3. from the bigrams it owns a batch adds up what its words follow and precede; these sums go the same way,
   by ranges of word hashes, and the totals come back;
4. with both answers a batch knows all counts its texts need. Each document is scored by the counts of all others
   (its own are taken off), so rare junk does not vouch for itself.

What travels are deltas of sorted hashes in compressed byte planes, some three bytes a distinct
bigram of a batch. Hashes have ``SPARE_BITS`` bits more than the text has bytes, so at any size about
one bigram in 2,000 shares its hash with another and is counted with it.

A language's documents give its bands: quartiles of the log perplexity, widened by ``BELOW`` and
``ABOVE`` times their distance, reject what lies outside.

Null and empty texts have no words and fail the base rules; texts of one word have no perplexity and pass
the bands; null languages are a language of their own; rows with equal or null ids are judged row by row; other
columns are carried by ``keep_good`` and ignored by ``verdicts``. A text longer than a batch is a batch.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterator

import numpy as np
import pandas as pd
import pyarrow as pa
import pyarrow.compute as pc
import zstandard
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from levelrank.llm.common import arrow_rows, release
from levelrank.plans.staging import discard, materialise, shared_path, small_rows

#: Distances of the quartiles by which the bands pass them. Copies make clean texts predictable, so the lower
#: band is wide; the upper one was set where half-random texts begin (README).
BELOW, ABOVE = 4.0, 1.5
#: Steps of the histogram per unit of log perplexity; rows that it and the language table may have.
STEPS, MAX_STEPS, MAX_LANGUAGES = 500, 2_000_000, 100_000
#: Bytes of text of a batch and of a hash range; bits of a bigram's hash beyond those of the text's size, and by which a word's is shorter.
BATCH_BYTES, RANGE_BYTES, SPARE_BITS, WORD_BITS = 8_000_000, 32_000_000, 6, 2
#: Bytes of text of a batch in ``keep_good``, whose tasks hold other columns too. The size changes memory and disk, no result.
SMALL_BATCH_BYTES = 4_000_000
#: Rejected rows that may be sent to every task (8 bytes each).
SENT_ROWS = 1_000_000
SYMBOLS, EDGES = r"[#*$%&|<>]", ".,;:!?\"'()[]{}|-–—«»„“”‘’¿¡"
OTHER = "?"
STATS = ("n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words")
U64 = np.uint64


# ---------------------------------------------------------------- packed arrays
def pack(values: np.ndarray) -> bytes:
    """Unsigned whole numbers as compressed byte planes."""
    values = np.ascontiguousarray(values, "<u8")
    planes = max(1, (int(values.max()).bit_length() + 7) // 8) if len(values) else 1
    raw = values.view(np.uint8).reshape(-1, 8)
    press = zstandard.ZstdCompressor(3)
    parts = [press.compress(np.ascontiguousarray(raw[:, k]).tobytes()) for k in range(planes)]
    return np.array([len(values), planes, *map(len, parts)], "<u4").tobytes() + b"".join(parts)


def unpack(blob: bytes) -> np.ndarray:
    n, planes = np.frombuffer(blob, "<u4", 2).tolist()
    sizes = np.frombuffer(blob, "<u4", planes, 8).tolist()
    out, at, open_ = np.zeros((n, 8), np.uint8), 8 + 4 * planes, zstandard.ZstdDecompressor()
    for k, size in enumerate(sizes):
        out[:, k] = np.frombuffer(open_.decompress(blob[at : at + size]), np.uint8)
        at += size
    return out.reshape(-1).view("<u8").astype(np.int64)


def deltas(sorted_values: np.ndarray) -> np.ndarray:
    return np.diff(sorted_values, prepend=np.int64(0))


def mix(x: np.ndarray) -> np.ndarray:
    x = x ^ (x >> U64(30))
    x = x * U64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> U64(27))
    x = x * U64(0x94D049BB133111EB)
    return x ^ (x >> U64(31))


def hashed(x: np.ndarray, bits: int) -> np.ndarray:
    return (mix(x.astype(U64)) >> U64(64 - bits)).astype(np.int64)


# ---------------------------------------------------------------- texts to arrays
def words_of(bodies: pa.Array) -> tuple[np.ndarray, np.ndarray, pa.Array]:
    """(place of each word among the distinct ones, text of each word, the distinct words), by ASCII white space."""
    cut = pc.ascii_split_whitespace(bodies.cast(pa.large_string()))
    flat = cut.flatten()
    owner = pc.list_parent_indices(cut).to_numpy()
    real = pc.not_equal(pc.binary_length(flat), 0)
    coded = flat.filter(real).dictionary_encode()
    return coded.indices.to_numpy().astype(np.int64), owner[real.to_numpy(zero_copy_only=False)], coded.dictionary


def _repeated(word: np.ndarray, owner: np.ndarray, kinds: int, n: int) -> np.ndarray:
    """Per text the words in three-word windows that the text holds twice or more."""
    if len(word) < 3:
        return np.zeros(n, np.int64)
    if kinds >= 1 << 21:
        _, pair = np.unique(word[:-1] * kinds + word[1:], return_inverse=True)
        key = pair[:-1] * kinds + word[2:]
    else:
        key = (word[:-2] * kinds + word[1:-1]) * kinds + word[2:]
    at = np.flatnonzero(owner[:-2] == owner[2:])
    at = at[np.argsort(key[at], kind="stable")]  # a text's windows of one kind stand side by side
    same = (key[at][1:] == key[at][:-1]) & (owner[at][1:] == owner[at][:-1])
    twice = at[np.r_[same, False] | np.r_[False, same]]
    edge = np.zeros(len(word) + 1, np.int32)
    np.add.at(edge, twice, 1)
    np.subtract.at(edge, twice + 3, 1)
    return np.bincount(owner[np.cumsum(edge)[:-1] > 0], minlength=n)


def statistics(bodies: pa.Array, word: np.ndarray, owner: np.ndarray, kinds: pa.Array) -> np.ndarray:
    """(texts, 5): the columns of ``STATS``."""
    n = len(bodies)
    chars = pc.utf8_length(kinds).to_numpy().astype(np.int64)
    cut = pc.split_pattern(bodies.cast(pa.large_string()), "\n")
    lines = cut.flatten()
    full = pc.not_equal(pc.binary_length(pc.ascii_trim_whitespace(lines)), 0)
    of = pc.list_parent_indices(cut).to_numpy()[full.to_numpy(zero_copy_only=False)]
    line = lines.filter(full).dictionary_encode().indices.to_numpy().astype(np.int64)
    firsts = np.unique(of * (len(lines) + 1) + line) // (len(lines) + 1)
    out = [
        np.bincount(owner, minlength=n), np.bincount(owner, chars[word], n).astype(np.int64), pc.count_substring_regex(bodies, SYMBOLS).to_numpy().astype(np.int64),
        np.bincount(of, minlength=n) - np.bincount(firsts, minlength=n), _repeated(word, owner, len(kinds), n),
    ]
    return np.stack(out, axis=1)


STREAM = "batch long, ids array<long>, langs array<string>, lang array<int>, stats array<long>, words binary, counts binary, tokens binary"


def streams(docs: DataFrame, id_col: str, bits: int, batch_bytes: int) -> DataFrame:
    """One row per batch of texts: ids, languages, statistics and the texts as places in the batch's sorted word hashes.

    ``counts`` says how often each word occurs; tokens number words by falling count, which keeps them small."""

    def make(part: list[pa.RecordBatch], number: int) -> pa.RecordBatch:
        table = pa.Table.from_batches(part)
        whole = lambda name, kind: pa.concat_arrays([c.cast(kind) for c in table.column(name).chunks])
        ids = whole(id_col, pa.int64())
        bodies, names = whole("text", pa.large_string()).fill_null(""), whole("lang", pa.string()).dictionary_encode()
        word, owner, kinds = words_of(bodies)
        stats = statistics(bodies, word, owner, kinds)
        del table, bodies
        plain = pc.utf8_trim(pc.utf8_lower(kinds), characters=EDGES).dictionary_encode()
        lang, langs, ids = names.indices.to_numpy().astype(np.int64), names.dictionary.to_pylist(), ids.to_pylist()
        base = pd.util.hash_array(plain.dictionary.to_numpy(zero_copy_only=False).astype(object), categorize=False)
        salt = pd.util.hash_array(np.array([f"language {x}" for x in langs], object), categorize=False)
        code = lang[owner] * (len(base) + 1) + plain.indices.to_numpy().astype(np.int64)[word]
        seen, at, n = np.unique(code, return_inverse=True, return_counts=True)
        key = hashed(base[seen % (len(base) + 1)] ^ mix(salt[seen // (len(base) + 1)]), bits - WORD_BITS) if len(seen) else np.zeros(0, np.int64)
        order = np.argsort(key, kind="stable")
        place = np.empty(len(order), np.int64)
        place[order] = np.arange(len(order))
        by_count = np.argsort(-n[order], kind="stable")
        rank = np.empty(len(order), np.int64)
        rank[by_count] = np.arange(len(order))
        rows = [[number], [ids], [langs], [lang.tolist()], [stats.ravel().tolist()], [pack(deltas(key[order]))], [pack(n[order])], [pack(rank[place][at])]]
        kinds_of = (pa.int64(), pa.list_(pa.int64()), pa.list_(pa.string()), pa.list_(pa.int32()), pa.list_(pa.int64()), pa.binary(), pa.binary(), pa.binary())
        return pa.record_batch([pa.array(x, k) for x, k in zip(rows, kinds_of)], [c.split()[0] for c in STREAM.split(", ")])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        from pyspark import TaskContext

        number, held, size = TaskContext.get().partitionId() << 32, [], 0
        for b in batches:
            if held and size + b.nbytes > batch_bytes:
                yield make(held, number)
                release()
                number, held, size = number + 1, [], 0
            held.append(b)
            size += b.nbytes
        if size or any(len(b) for b in held):
            yield make(held, number)

    named = docs.select(F.col(id_col).cast("long").alias(id_col), F.coalesce("lang", F.lit(OTHER)).alias("lang"), "text")
    return arrow_rows(named, [id_col, "lang", "text"], run, STREAM, batch_bytes)


def one_by_one(batches: Iterator[pa.RecordBatch]) -> Iterator[dict]:
    """Rows as Python values, one at a time; memory that the last one took goes back."""
    for b in batches:
        for k in range(len(b)):
            yield from b.slice(k, 1).to_pylist()
            release()


class Batch:
    """A row of the stream table: word hashes, words by text, and bigrams in the order of their hashes."""

    def __init__(self, row: dict, bits: int):
        self.ids, self.langs, self.lang = row["ids"], row["langs"], np.array(row["lang"], np.int64)
        self.stats = np.array(row["stats"], np.int64).reshape(-1, len(STATS))
        self.keys, counts = np.cumsum(unpack(row["words"])), unpack(row["counts"])
        self.counts = counts
        self.words = np.argsort(-counts, kind="stable").astype(np.int32)[unpack(row["tokens"])] if len(counts) else np.zeros(0, np.int32)
        self.owner = np.repeat(np.arange(len(self.ids), dtype=np.int32), self.stats[:, 0])
        first = np.flatnonzero(self.owner[1:] == self.owner[:-1]).astype(np.int32)
        self.first, self.text = first, self.owner[first]
        size = max(1, len(self.keys))
        seen, at, n = np.unique(self.words[first].astype(np.int64) * size + self.words[first + 1], return_inverse=True, return_counts=True)
        at, n, u, w = at.astype(np.int32), n.astype(np.int32), (seen // size).astype(np.int32), (seen % size).astype(np.int32)
        key = hashed(mix(self.keys.astype(U64))[u] * U64(3) ^ self.keys.astype(U64)[w], bits) if len(seen) else seen
        del seen
        order = np.argsort(key, kind="stable").astype(np.int32)
        place = np.empty(len(order), np.int32)
        place[order] = np.arange(len(order), dtype=np.int32)
        self.bigrams, self.n, self.u, self.w, self.at = key[order], n[order], u[order], w[order], place[at]
        self.word_lang = np.zeros(len(self.keys), np.int64)
        self.word_lang[self.words] = self.lang[self.owner]


def _ranges(keys: np.ndarray, bits: int, range_bits: int) -> list[tuple[int, int, int]]:
    """(range, start, end) of the hash ranges that sorted ``keys`` fall into."""
    part = keys >> (bits - range_bits)
    starts = np.flatnonzero(np.r_[True, part[1:] != part[:-1]]) if len(part) else np.zeros(0, np.int64)
    return [(int(part[a]), int(a), int(z)) for a, z in zip(starts, np.r_[starts[1:], len(part)])]


SENT = "kind int, batch long, part int, lang string, totals array<long>, blobs array<binary>"
_SENT_TYPES = (pa.int32(), pa.int64(), pa.int32(), pa.string(), pa.list_(pa.int64()), pa.list_(pa.binary()))
REQUEST, STATISTIC, BIGRAMS, WORDS, TOTAL = range(5)


def _sent(rows: list[tuple]) -> pa.Table:
    return pa.table([pa.array([r[i] for r in rows], t) for i, t in enumerate(_SENT_TYPES)], names=[c.split()[0] for c in SENT.split(", ")])


def _merge(rows: list[dict]) -> tuple[np.ndarray, np.ndarray, np.ndarray]:
    """Of requests: their keys' places in the merged sorted array, first places of that array's keys, request bounds."""
    keys = [np.cumsum(unpack(r["blobs"][0])) for r in rows]
    _, first, at = np.unique(np.concatenate(keys), return_index=True, return_inverse=True)
    return at, first, np.cumsum([0, *map(len, keys)])


def _requests(table: pa.Table) -> list[dict]:
    return sorted((r for r in table.select(["kind", "batch", "part", "blobs"]).to_pylist() if r["kind"] == REQUEST), key=lambda r: r["batch"])


def bigram_counts(stream: DataFrame, bits: int, range_bits: int) -> DataFrame:
    """Answers (kind BIGRAMS) to every batch: counts of its bigrams over all documents, and whether the batch owns them."""

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in one_by_one(batches):
            x = Batch(row, bits)
            rows = [(REQUEST, row["batch"], k, None, None, [pack(deltas(x.bigrams[a:z])), pack(x.n[a:z])]) for k, a, z in _ranges(x.bigrams, bits, range_bits)]
            yield from _sent(rows).to_batches()

    def answer(table: pa.Table) -> pa.Table:
        release()
        rows = _requests(table)
        at, first, bounds = _merge(rows)
        total = np.bincount(at, np.concatenate([unpack(r["blobs"][1]) for r in rows])).astype(np.int64)
        own = np.zeros(len(at), bool)
        own[first] = True
        return _sent([(BIGRAMS, r["batch"], r["part"], None, None, [pack(total[at[a:z]]), pack(own[a:z])]) for r, a, z in zip(rows, bounds, bounds[1:])])

    return stream.mapInArrow(ask, SENT).groupBy("part").applyInArrow(answer, SENT)


def placed(answers: DataFrame, buckets: int, tables: dict[str, str]) -> DataFrame:
    """The answers written once, dealt by batch into as many buckets as the streams, so that joins with them move neither."""
    spark, name = answers.sparkSession, f"lr_answers_{uuid.uuid4().hex}"
    tables[name] = shared_path(spark, "answers")
    answers.repartition(buckets, "batch").write.bucketBy(buckets, "batch").option("path", tables[name]).saveAsTable(name)
    return spark.table(name)


def by_batch(answers: DataFrame, kind: int) -> DataFrame:
    """(batch, answers): one row per batch, grouped in place."""
    return answers.where(F.col("kind") == kind).groupBy("batch").agg(F.collect_list(F.struct("part", "blobs")).alias(f"answers{kind}")).hint("merge")


def _answers(rows: list[dict] | None) -> list[np.ndarray]:
    """A batch's answers, ranges in order, as whole arrays."""
    rows = sorted(rows or [], key=lambda r: r["part"])
    return [np.concatenate([unpack(r["blobs"][k]) for r in rows]) for k in range(len(rows[0]["blobs"]))] if rows else []


def word_requests(answered: DataFrame, bits: int, range_bits: int) -> DataFrame:
    """Per batch and range of word hashes (kind REQUEST): occurrences, occurrences as a context, bigrams owned by context (seen
    once, twice, more often) and by ending; and (kind STATISTIC) how many owned bigrams of a language were seen one to four times.
    ``answered``: streams with their bigrams' answers."""

    def ask(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in one_by_one(batches):
            x, out = Batch(row, bits), []
            size = len(x.keys)
            total, own = _answers(row[f"answers{BIGRAMS}"]) or (np.zeros(0, np.int64),) * 2
            mine = own > 0
            u, w, c = x.u[mine], x.w[mine], np.minimum(total[mine], 5)
            sums = [x.counts, np.bincount(x.u, x.n, size).astype(np.int64), *(np.bincount(u[(c == k) if k < 3 else (c > 2)], minlength=size) for k in (1, 2, 3)), np.bincount(w, minlength=size), x.word_lang]
            for k, a, z in _ranges(x.keys, bits - WORD_BITS, range_bits):
                out.append((REQUEST, row["batch"], k, None, None, [pack(deltas(x.keys[a:z])), *(pack(s[a:z]) for s in sums), "\0".join(x.langs).encode()]))
            seen = np.bincount(x.word_lang[w] * 6 + c, minlength=6 * len(x.langs)).reshape(-1, 6)
            out += [(STATISTIC, row["batch"], 0, name, n[1:5].tolist(), None) for name, n in zip(x.langs, seen)]
            yield from _sent(out).to_batches()

    return answered.mapInArrow(ask, SENT)


def word_totals(requests: DataFrame) -> DataFrame:
    """Answers (kind WORDS) with the sums over all batches, and (kind TOTAL) per language: words, bigrams, words that end none to four of them. Rows of kind STATISTIC pass."""

    def answer(table: pa.Table) -> pa.Table:
        release()
        rows, passed = _requests(table), table.filter(pc.equal(table.column("kind"), STATISTIC))
        if not rows:
            return passed
        at, first, bounds = _merge(rows)
        sums = [np.bincount(at, np.concatenate([unpack(r["blobs"][k]) for r in rows])).astype(np.int64) for k in range(1, 7)]
        names = [r["blobs"][8].decode().split("\0") for r in rows]
        langs = sorted({x for n in names for x in n})
        code = np.concatenate([np.array([langs.index(x) for x in n], np.int64)[unpack(r["blobs"][7])] for n, r in zip(names, rows)])[first]
        out = [(WORDS, r["batch"], r["part"], None, None, [pack(s[at[a:z]]) for s in sums]) for r, a, z in zip(rows, bounds, bounds[1:])]
        ends = sums[5]
        for k, name in enumerate(langs):
            own = ends[code == k]
            out.append((TOTAL, None, None, name, [len(own), int(own.sum()), *(int((own == i).sum()) for i in range(5))], None))
        return pa.concat_tables([_sent(out), passed.cast(_sent([]).schema)])

    return requests.groupBy("part").applyInArrow(answer, SENT)


def discounts(n1: int, n2: int, n3: int, n4: int) -> np.ndarray:
    """What counts of none, one, two and more lose."""
    if not n1 or not n2 or not n3:
        return np.array([0.0, 0.5, 1.0, 1.5])  # too little text for the estimates
    y = n1 / (n1 + 2 * n2)
    d = (1 - 2 * y * n2 / n1, 2 - 3 * y * n3 / n2, 3 - 4 * y * n4 / n3)
    return np.array([0.0, *(min(max(x, 0.05), k + 0.95) for k, x in enumerate(d))])


def constants(totals: DataFrame) -> dict[str, tuple]:
    """Per language: discounts of bigrams and of endings, words, bigrams, and the mass that endings' discounts free."""
    sums = lambda kind, n: small_rows(totals.where(F.col("kind") == kind).groupBy("lang").agg(*(F.sum(F.get("totals", F.lit(i))).alias(f"t{i}") for i in range(n))), MAX_LANGUAGES, "languages")
    seen, out = {r.lang: r[1:] for r in sums(STATISTIC, 4)}, {}
    for r in sums(TOTAL, 7):
        words, bigrams, none, *ends = r[1:]
        d = discounts(*ends)
        freed = d[1] * ends[0] + d[2] * ends[1] + d[3] * (words - none - ends[0] - ends[1])
        out[r.lang] = (discounts(*seen.get(r.lang, (0, 0, 0, 0))), d, words, bigrams, freed / bigrams if bigrams else 1.0)
    return out


def surprises(answered: DataFrame, of_lang: dict[str, tuple], bits: int, id_col: str) -> DataFrame:
    """One row per document: id, language, statistics and the mean negative log probability of a word given the one before.
    ``answered``: streams with their bigrams' and words' answers."""
    shared = answered.sparkSession.sparkContext.broadcast(of_lang)

    def score(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for row in one_by_one(batches):
            x = Batch(row, bits)
            mean = np.full(len(x.ids), np.nan)
            if len(x.first):
                mean = document_surprise(x, _answers(row[f"answers{BIGRAMS}"])[0], _answers(row[f"answers{WORDS}"]), [shared.value[n] for n in x.langs])
            yield pa.record_batch([pa.array(x.ids, pa.int64()), pa.array([x.langs[k] for k in x.lang.tolist()], pa.string()), *(pa.array(x.stats[:, k]) for k in range(len(STATS))), pa.array(mean, pa.float64(), from_pandas=True)], [id_col, "lang", *STATS, "surprise"])

    return answered.mapInArrow(score, f"{id_col} long, lang string, {', '.join(f'{c} long' for c in STATS)}, surprise double")


def _own(text: np.ndarray, what: np.ndarray, size: int) -> np.ndarray:
    """How often the own text holds each of ``what``."""
    _, at, n = np.unique(text.astype(np.int64) * size + what, return_inverse=True, return_counts=True)
    return n[at]


def probabilities(c, c_u, free_u, ends_w, seen_w, cut, cut_end, words, bigrams, freed) -> np.ndarray:
    """Interpolated modified Kneser-Ney: counts of the bigram and its context, mass that the context frees, what the
    word ends, and whether it is seen at all; then the language's constants, one row per bigram."""
    at = np.arange(len(c))
    high = np.where(c > 0, (c - cut[at, np.minimum(c, 3)]) / np.maximum(c_u, 1), 0.0)
    low = np.where(seen_w, (ends_w - cut_end[at, np.minimum(ends_w, 3)]) / np.maximum(bigrams, 1), 0.0) + freed / np.maximum(words, 1)
    return np.maximum(high, 0.0) + np.where(c_u > 0, free_u, 1.0) * np.maximum(low, 1e-300)


def document_surprise(x: Batch, total: np.ndarray, words: list[np.ndarray], of_lang: list[tuple]) -> np.ndarray:
    """Mean over each text's bigrams, by the counts of all other texts."""
    occurs, as_context, n1, n2, n3, ends = words
    lang = x.lang[x.text]
    cut, cut_end = (np.stack([k[i] for k in of_lang])[lang] for i in (0, 1))
    many = [np.array([k[i] for k in of_lang], float)[lang] for i in (2, 3, 4)]
    u, w, size = x.u[x.at], x.w[x.at], len(x.keys)
    free = (cut[:, 1] * n1[u] + cut[:, 2] * n2[u] + cut[:, 3] * n3[u]) / np.maximum(as_context[u], 1)
    c, c_u = total[x.at] - _own(x.text, x.at, len(x.bigrams)), as_context[u] - _own(x.text, u, size)
    mine = _own(x.owner, x.words, size)[x.first + 1]
    p = probabilities(np.maximum(c, 0), np.maximum(c_u, 0), free, ends[w], occurs[w] > mine, cut, cut_end, *many)
    n = np.bincount(x.text, minlength=len(x.ids))
    return np.where(n > 0, np.bincount(x.text, -np.log(p), len(x.ids)) / np.maximum(n, 1), np.nan)


def measures(docs: DataFrame, id_col: str = "doc_id", batch_bytes: int | None = None) -> DataFrame:
    """One row per row of ``docs``: id, language, statistics and surprise (null under two words)."""
    spark, batch_bytes = docs.sparkSession, batch_bytes or BATCH_BYTES
    size = docs.agg(F.sum(F.octet_length("text"))).first()[0] or 0
    bits = min(60, SPARE_BITS + max(28, int(size).bit_length()))
    range_bits = min(bits - 8, max(1, int(size // RANGE_BYTES).bit_length()))
    name = f"lr_streams_{uuid.uuid4().hex}"
    buckets, tables = int(min(50_000, max(4, 2 * size // batch_bytes))), {name: shared_path(spark, "streams")}
    streams(docs, id_col, bits, batch_bytes).write.bucketBy(buckets, "batch").option("path", tables[name]).saveAsTable(name)
    stream = spark.table(name)
    counted = placed(bigram_counts(stream, bits, range_bits), buckets, tables)
    answered = stream.join(by_batch(counted, BIGRAMS), "batch", "left")
    totals = placed(word_totals(word_requests(answered, bits, range_bits)), buckets, tables)
    scored = answered.join(by_batch(totals, WORDS), "batch", "left")
    out = materialise(surprises(scored, constants(totals), bits, id_col), "quality")
    for name in tables:  # what ``out`` holds is written: nothing reads these any more
        spark.sql(f"DROP TABLE {name}")
    discard(spark, *tables.values())
    return out


# ---------------------------------------------------------------- verdicts
FAILED = "(n_words < 50 or 100 * n_repeat_words > 50 * n_words)"


def bands(measured: DataFrame, below: float = BELOW, above: float = ABOVE) -> DataFrame:
    """(lang, low, high) surprise per language, from the documents that pass the base rules."""
    fit = measured.where(f"not {FAILED} and surprise is not null")
    steps = fit.groupBy("lang", F.round(F.col("surprise") * STEPS).cast("int").alias("step")).agg(F.count("*").alias("n"))  # a histogram: exact counts, so reruns agree
    of: dict[str, list[tuple[int, int]]] = {}
    for r in small_rows(steps, MAX_STEPS, "histogram"):
        of.setdefault(r.lang, []).append((r.step, r.n))
    out = []
    for lang, rows in of.items():
        rows.sort()
        upto = np.cumsum([n for _, n in rows])
        low, high = (rows[int(np.searchsorted(upto, q * upto[-1]))][0] / STEPS for q in (0.25, 0.75))
        wide = max(0.05, high - low)
        out.append((lang, float(low - below * wide), float(high + above * wide)))
    return measured.sparkSession.createDataFrame(sorted(out), "lang string, low double, high double")


def judged(measured: DataFrame) -> DataFrame:
    """Adds base_failed and kept; documents without a perplexity stay unless the base rules reject them."""
    inside = F.coalesce(F.col("surprise").between(F.col("low"), F.col("high")), F.lit(True))
    return measured.join(F.broadcast(bands(measured)), "lang", "left").withColumn("base_failed", F.expr(FAILED)).withColumn("kept", ~F.col("base_failed") & inside)


def verdicts(docs: DataFrame) -> DataFrame:
    """doc_id, statistics, base_failed, kept, perplexity: one row per row of ``docs``."""
    return judged(measures(docs)).select("doc_id", *STATS, "base_failed", "kept", F.exp("surprise").alias("perplexity"))


def keep_good(docs: DataFrame) -> DataFrame:
    """The rows that pass, all columns unchanged. Rows get a number that is written once with them; the
    numbers of rejected rows come back, by broadcast up to ``SENT_ROWS`` and by a join beyond."""
    row = "row_number"
    while row.lower() in {c.lower() for c in docs.columns}:
        row += "_"
    numbered = materialise(docs.withColumn(row, F.monotonically_increasing_id()), "numbered")
    gone = judged(measures(numbered.select(row, "lang", "text"), row, SMALL_BATCH_BYTES)).where(~F.col("kept")).select(row)
    few = gone.limit(SENT_ROWS + 1).count() <= SENT_ROWS
    return numbered.join(F.broadcast(gone) if few else gone, row, "left_anti").select(*docs.columns)
