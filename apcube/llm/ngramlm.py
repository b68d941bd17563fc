"""Word-trigram language model by deleted interpolation, and the score of every document under it.

P(w | u, v) = l3 c(u, v, w) / c(u, v) + l2 c(v, w) / c(v) + l1 c(w) / N + l0 / (V + 1). The weights depend on the bucket of
the context's frequency: that of c(u, v) where the pair was seen, of c(v) where it wasn't. They come from
expectation-maximisation on deleted counts: for every training token, the counts without those of its own document.

How counts meet tokens. Tokens are packed into *chunks* of whole documents, each a row of compressed arrays. A chunk
sends its distinct words, bigrams and trigrams, with their counts in its training documents, to FAN nodes that own a
range of the keys' hashes each. While there are more chunks than FAN, a node serves a group of FAN chunks alone: it
merges what they sent and passes it on, cut into FAN finer ranges, to the nodes of the next level, so that a node of any
level holds about as many keys as a chunk. The last level adds up, and answers go back the same way. Rows are FAN a
chunk and level, and levels the logarithm of the number of chunks to the base FAN: they grow as the corpus does (times
that logarithm), tasks don't grow. A word in every document costs one entry a chunk. Nothing is broadcast but the weights.

Keys of words are 64-bit hashes. Those of bigrams and trigrams have MORE_BITS bits more than are needed to number the
corpus's tokens (40 at least), which halves what is sent: one n-gram in 2**MORE_BITS, about, shares its count with another.
"""

from __future__ import annotations

import math
import uuid
import zlib
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
import zstandard
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from apcube.llm.storage import materialize
from apcube.llm.wordhash import BASE, hash_words, mix, slices, text_buffers

#: Tokens of a chunk, about; FAN is 2**FAN_BITS.
CHUNK_TOKENS, FAN_BITS, MORE_BITS = 1_000_000, 7, 16
#: Buckets of seen pairs (powers of two, the last open) and of the last word where the pair is new (0 for a new word).
PAIRS, SINGLES = 20, 40
BUCKETS = PAIRS + SINGLES
#: Ratios are gathered in steps of 1/STEPS of a power of two, down to 2**-LOW.
STEPS, LOW = 2, 26
GRID = STEPS * LOW + 2
END, START, START2 = np.uint64(0x0E0F0E0F0E0F0E0F), np.uint64(0x57A7), np.uint64(0x57A757A7)
CHUNK = "chunk string, ids binary, tokens binary, lengths binary, words binary, counted binary"
MESSAGE = "grp int, reach bigint, sender string, digit int, keys array<binary>, counts array<binary>"
ANSWER = "sender string, digit int, extra array<binary>, distinct bigint, tokens bigint"


def _pack(x: np.ndarray) -> bytes:
    return zstandard.ZstdCompressor(level=1).compress(np.ascontiguousarray(x).view(np.uint8).reshape(len(x), -1).T.tobytes() if len(x) else b"")


def _unpack(raw: bytes, kind: str) -> np.ndarray:
    flat = np.frombuffer(zstandard.ZstdDecompressor().decompress(raw), np.uint8)
    return np.ascontiguousarray(flat.reshape(np.dtype(kind).itemsize, -1).T).view(kind).ravel()


def _deltas(keys: np.ndarray) -> np.ndarray:
    return np.diff(keys, prepend=np.uint64(0))


def _chunks(docs: DataFrame) -> DataFrame:
    """docs: row_id, text, counted -> chunks. Documents are ``lengths`` tokens each, the end token included."""

    def flush(held: list) -> pa.RecordBatch:
        hashes = np.concatenate([h for h, *_ in held])
        words, tokens = np.unique(hashes, return_inverse=True)
        lengths, counted = (np.concatenate([x[k] for x in held]) for k in (1, 2))
        ids = pa.concat_arrays([x[3] for x in held])
        sink = pa.BufferOutputStream()
        batch = pa.record_batch([ids], ["doc_id"])
        with pa.ipc.new_stream(sink, batch.schema, options=pa.ipc.IpcWriteOptions(compression="zstd")) as out:
            out.write_batch(batch)
        row = [uuid.uuid4().hex, sink.getvalue().to_pybytes(), _pack(tokens.astype(np.uint32)), _pack(lengths.astype(np.uint32)), _pack(_deltas(words)), _pack(counted.astype(np.uint8))]
        return pa.record_batch([pa.array([x]) for x in row], ["chunk", "ids", "tokens", "lengths", "words", "counted"])

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        held, size = [], 0
        for part in slices(batches, "text", 4 << 20):
            w = hash_words(*text_buffers(part.column("text")))
            n = w.per_doc
            hashes = np.insert(w.hash, w.bounds[1:], END)
            held.append((hashes, n + 1, part.column("counted").to_numpy(zero_copy_only=False), part.column("doc_id")))
            size += len(hashes)
            if size >= CHUNK_TOKENS:
                yield flush(held)
                held, size = [], 0
        if held:
            yield flush(held)

    return docs.mapInArrow(run, CHUNK)


class _Chunk:
    """A chunk's arrays. Per order (words, bigrams, trigrams): ``of`` each token's n-gram, ``keys`` their hashes, ``own``
    their counts in the chunk's training documents, ``sent`` the order in which they are sent (by key)."""

    def __init__(self, row: dict, bits: int):
        tokens = _unpack(row["tokens"], "u4")
        self.lengths = _unpack(row["lengths"], "u4").astype(np.int64)
        words = np.cumsum(_unpack(row["words"], "u8"))
        self.counted = _unpack(row["counted"], "u1").astype(bool)
        self.first = np.concatenate([[0], np.cumsum(self.lengths)])[:-1]
        self.train = np.repeat(self.counted, self.lengths)
        hashes, last, self.of, self.keys, self.before = words, tokens, [tokens.astype(np.int64)], [words], []
        for start in (START, START2):
            context = np.empty(len(tokens), np.uint64)
            context[1:] = last[:-1]
            context[self.first] = len(hashes)  # the start of a document
            runs, last = np.unique(context << np.uint64(32) | tokens, return_inverse=True)
            hashes = mix(np.append(hashes, start)[runs >> np.uint64(32)] * BASE + mix(words[runs & np.uint64(0xFFFFFFFF)] ^ start))
            self.before.append(context.astype(np.int64))
            self.of.append(last)
            self.keys.append(hashes >> np.uint64(64 - bits))
        self.own = [np.bincount(of[self.train], minlength=len(k)) for of, k in zip(self.of, self.keys)]
        self.sent = [np.argsort(k, kind="stable") for k in self.keys]

    def totals(self, answers: list[dict]) -> list[np.ndarray]:
        """Per order the corpus counts of the chunk's n-grams."""
        out = []
        for order, (own, sent) in enumerate(zip(self.own, self.sent)):
            total = np.empty(len(own), np.int64)
            total[sent] = own[sent] + _joined(answers, order)
            out.append(total)
        return out


def _joined(answers: list[dict], order: int) -> np.ndarray:
    return np.concatenate([_unpack(r["extra"][order], "u8") for r in sorted(answers, key=lambda r: r["digit"])] or [np.empty(0, np.uint64)]).astype(np.int64)


def _messages(grp: int, reach: int, sender: str, keys: list[np.ndarray], counts: list[np.ndarray], level: int, bits: int) -> pa.RecordBatch:
    """Rows that send ascending keys of the range ``reach``, whose level is one less than ``level``, by their next digit."""
    fan, cuts = 1 << FAN_BITS, []
    for order, k in enumerate(keys):
        width = bits if order else 64
        digit = k >> np.uint64(width - FAN_BITS * level) & np.uint64(fan - 1)
        cuts.append(np.searchsorted(digit, np.arange(fan + 1, dtype=np.uint64)))
    some = [d for d in range(fan) if any(c[d] < c[d + 1] for c in cuts)]
    part = lambda x, pack: [[pack(v[c[d] : c[d + 1]]) for v, c in zip(x, cuts)] for d in some]
    n = len(some)
    columns = [pa.array([grp] * n, pa.int32()), pa.array([reach * fan + d for d in some], pa.int64()), pa.array([sender] * n, pa.string()), pa.array(some, pa.int32())]
    columns += [pa.array(part(keys, lambda v: _pack(_deltas(v))), pa.list_(pa.binary())), pa.array(part(counts, lambda v: _pack(v.astype(np.uint64))), pa.list_(pa.binary()))]
    return pa.RecordBatch.from_arrays(columns, [x.split()[0] for x in MESSAGE.split(", ")])


def _ask(chunks: DataFrame, groups: int, bits: int) -> DataFrame:
    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            for row in batch.to_pylist():
                c = _Chunk(row, bits)
                yield _messages(zlib.crc32(row["chunk"].encode()) % groups, 0, row["chunk"], [k[s] for k, s in zip(c.keys, c.sent)], [n[s] for n, s in zip(c.own, c.sent)], 1, bits)

    return chunks.mapInArrow(run, MESSAGE)


class _Node:
    """What the messages to a node hold together: per order its keys, ascending, their counts, and for each message where
    its keys are among them."""

    def __init__(self, rows: list[dict]):
        self.rows, self.keys, self.counts, self.at, self.asked = rows, [], [], [], []
        for order in range(3):
            keys = [np.cumsum(_unpack(r["keys"][order], "u8")) for r in rows]
            counts = [_unpack(r["counts"][order], "u8").astype(np.int64) for r in rows]
            known, at = np.unique(np.concatenate(keys), return_inverse=True)
            self.keys.append(known)
            self.counts.append(np.bincount(at, np.concatenate(counts), len(known)).astype(np.int64))
            self.at.append(np.split(at, np.cumsum([len(k) for k in keys])[:-1]))
            self.asked.append(counts)

    def answers(self, totals: list[np.ndarray]) -> pa.RecordBatch:
        """Per message the totals of its keys beyond the counts that it sent itself."""
        extra = [[_pack((totals[o][self.at[o][i]] - self.asked[o][i]).astype(np.uint64)) for o in range(3)] for i in range(len(self.rows))]
        n = len(self.rows)
        return _answer_rows([r["sender"] for r in self.rows], [r["digit"] for r in self.rows], extra, [None] * n, [None] * n)


def _answer_rows(*columns: list) -> pa.RecordBatch:
    kinds = [pa.string(), pa.int32(), pa.list_(pa.binary()), pa.int64(), pa.int64()]
    return pa.RecordBatch.from_arrays([pa.array(x, k) for x, k in zip(columns, kinds)], [x.split()[0] for x in ANSWER.split(", ")])


def _rows(batches: Iterator[pa.RecordBatch]) -> list[dict]:
    return [r for b in batches for r in b.to_pylist()]


def _up(messages: DataFrame, level: int, groups: int, bits: int) -> DataFrame:
    """The messages of nodes of ``level`` to those of the next."""

    def run(table: pa.Table) -> pa.Table:
        rows = _rows(table.to_batches())
        node, r = _Node(rows), rows[0]
        return pa.Table.from_batches([_messages(r["grp"] % groups, r["reach"], f"{r['grp']}:{r['reach']}", node.keys, node.counts, level + 1, bits)])

    return messages.groupBy("grp", "reach").applyInArrow(run, MESSAGE)


def _top(messages: DataFrame) -> DataFrame:
    """Answers of the last level; per node also, in a row without sender, the number of words and their sum."""

    def run(table: pa.Table) -> pa.Table:
        node = _Node(_rows(table.to_batches()))
        words = node.counts[0]
        sums = _answer_rows([None], [None], [None], [int((words > 0).sum())], [int(words.sum())])
        return pa.Table.from_batches([node.answers(node.counts), sums])

    return messages.groupBy("reach").applyInArrow(run, ANSWER)


def _down(messages: DataFrame, answers: DataFrame) -> DataFrame:
    """Answers of the nodes that got ``messages``, from those that they got themselves."""

    def run(left: pa.Table, right: pa.Table) -> pa.Table:
        node, got = _Node(_rows(left.to_batches())), _rows(right.to_batches())
        return pa.Table.from_batches([node.answers([c + _joined(got, o) for o, c in enumerate(node.counts)])])

    keyed = messages.withColumn("node", F.concat_ws(":", "grp", "reach"))
    return keyed.groupBy("node").cogroup(answers.where("sender is not null").groupBy("sender")).applyInArrow(run, ANSWER)


def bucket(pair: np.ndarray, single: np.ndarray) -> np.ndarray:
    """The weights' bucket of a context: by the frequency of its last two words, or of the last where the two are new."""
    log = lambda x: np.floor(np.log2(np.maximum(x, 1))).astype(np.int64)
    return np.where(pair > 0, SINGLES + np.minimum(log(pair), PAIRS - 1), np.where(single > 0, np.minimum(log(single) + 1, SINGLES - 1), 0))


def _cell(ratio: np.ndarray) -> np.ndarray:
    """A step of the ratio's logarithm; the last for 0."""
    out = np.full(len(ratio), GRID - 1, np.int64)
    some = ratio > 0
    out[some] = np.clip(np.round(-np.log2(ratio[some]) * STEPS), 0, GRID - 2).astype(np.int64)
    return out


def _share(part: np.ndarray, whole: np.ndarray) -> np.ndarray:
    return np.where(whole > 0, part / np.maximum(whole, 1), 0.0)


def _frequencies(c: _Chunk, totals: list[np.ndarray], train_docs: int) -> tuple[list[np.ndarray], list[np.ndarray]]:
    """Per token the counts of its word, bigram and trigram, and those of its contexts of one and two words."""
    count = [t[of] for t, of in zip(totals, c.of)]
    return count, [np.append(t, train_docs)[b] for t, b in zip(totals, c.before)]


def _histogram(c: _Chunk, totals: list[np.ndarray], train_docs: int, train_tokens: int) -> tuple[np.ndarray, np.ndarray]:
    """(cells, tokens): training tokens by bucket and ratios of trigram, bigram and word, from counts without their own
    document."""
    doc = np.repeat(np.arange(len(c.lengths), dtype=np.uint64), c.lengths)

    def own(key: np.ndarray) -> np.ndarray:
        _, at, n = np.unique(doc << np.uint64(32) | key.astype(np.uint64), return_inverse=True, return_counts=True)
        return n[at]

    count, context = _frequencies(c, totals, train_docs)
    mine = [own(of) for of in c.of]
    starts = np.zeros(len(doc), bool)
    starts[c.first] = True
    # a context's own count: that of the n-gram before, 1 for the start of the document
    c1, c2, c3 = ((n - o)[c.train] for n, o in zip(count, mine))
    h1, h2 = ((n - np.where(starts, 1, np.roll(o, 1)))[c.train] for n, o in zip(context, mine))
    left = train_tokens - np.repeat(c.lengths, c.lengths)[c.train]
    cells = bucket(h2, h1)
    for ratio in (_share(c3, h2), _share(c2, h1), _share(c1, left)):
        cells = cells * GRID + _cell(ratio)
    return np.unique(cells, return_counts=True)


def estimate(cells: np.ndarray, tokens: np.ndarray, vocabulary: int, rounds: int = 200) -> np.ndarray:
    """Weights (bucket, [trigram, bigram, word, uniform]) by expectation-maximisation. A new pair has no trigram weight, a
    new word no bigram weight either; every other weight is at least 1e-6, so that no text gets probability 0. A bucket
    without tokens takes the weights of the nearest lower one of its kind that has any."""
    value = np.append(2.0 ** (-np.arange(GRID - 1) / STEPS), 0.0)
    b, ratios = cells // GRID**3, [value[cells // GRID**k % GRID] for k in (2, 1, 0)]
    out = np.zeros((BUCKETS, 4))
    if not tokens.sum():
        out[:, 3] = 1.0
        return out
    for k in range(BUCKETS):
        may = np.array([k >= SINGLES, k > 0, True, True], float)
        mine = b == k
        n = tokens[mine].astype(float)
        if n.sum():
            p = np.stack([*(r[mine] for r in ratios), np.full(mine.sum(), 1 / (vocabulary + 1))])
            w = may / may.sum()
            for _ in range(rounds):
                part = w[:, None] * p
                part /= part.sum(axis=0)
                w = part @ n
                w /= w.sum()
            w = np.maximum(w, 1e-6 * may)
        elif k in (0, 1, SINGLES):
            w = may * np.array([0.3, 0.3, 0.3, 0.1])
        out[k] = w / w.sum()
    return out


SCORES = "n_tokens bigint, n_known bigint, train_tokens bigint, base_score double, score double"


def _scores(c: _Chunk, totals: list[np.ndarray], weights: np.ndarray, train_docs: int, train_tokens: int, vocabulary: int) -> list[np.ndarray]:
    (c1, c2, c3), (h1, h2) = _frequencies(c, totals, train_docs)
    w = weights[bucket(h2, h1)]
    score = np.log10(w[:, 0] * _share(c3, h2) + w[:, 1] * _share(c2, h1) + w[:, 2] * (c1 / max(train_tokens, 1)) + w[:, 3] / (vocabulary + 1))
    base = np.log10((c1 + 1) / (train_tokens + vocabulary + 1))
    known, base, score = (np.add.reduceat(x, c.first) for x in ((c1 > 0).astype(np.int64), base, score))
    return [c.lengths, known, np.full(len(known), train_tokens), base, score]


def score(docs: DataFrame, counted: Column, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """Per row: doc_id, counted boolean, n_tokens, n_known, train_tokens long, base_score, score double.

    The model is learned from rows where ``counted``; a row where that is null isn't learned from. A null or empty text is
    its end token alone. Tokens are words with A-Z in lower case, then one end. ``base_score``: log10 of add-one unigrams;
    ``score``: log10 of the interpolated model, finite for every text. Rows of equal text get equal results. Without
    training rows all scores are those of the uniform model. An empty table gives no rows.
    """
    narrow = docs.select(F.col(id_col).alias("doc_id"), F.col(text_col).cast("string").alias("text"), F.coalesce(counted, F.lit(False)).alias("counted"))
    kind = narrow.schema["doc_id"].dataType.simpleString()
    chunks = materialize(_chunks(narrow), "chunks")
    train_docs, number = narrow.where("counted").count(), chunks.count()
    bits = min(64, max(40, math.ceil(math.log2(max(1, number * CHUNK_TOKENS))) + MORE_BITS))
    groups = [number]  # of chunks, then of the groups of nodes that serve them, level by level
    while groups[-1] > 1 or len(groups) == 1:
        groups.append(-(-groups[-1] // (1 << FAN_BITS)))
    if FAN_BITS * (len(groups) - 1) > 40:
        raise ValueError("FAN_BITS is too small for so many chunks")
    sent = [_ask(chunks, max(1, groups[1]), bits)]
    for level in range(1, len(groups) - 1):
        sent[-1] = materialize(sent[-1], "messages")
        sent.append(_up(sent[-1], level, groups[level + 1], bits))
    answers = materialize(_top(sent.pop()), "answers")
    sums = answers.where("sender is null").agg(F.sum("distinct").alias("v"), F.sum("tokens").alias("n")).first()
    vocabulary, train_tokens = int(sums["v"] or 0), int(sums["n"] or 0)
    while sent:
        answers = materialize(_down(sent.pop(), answers), "answers")
    replies = answers.where("sender is not null").select("sender", "digit", "extra")

    def counted_chunk(left: pa.Table, right: pa.Table) -> tuple[dict, _Chunk, list[np.ndarray]]:
        row = left.to_pylist()[0]
        c = _Chunk(row, bits)
        return row, c, c.totals(right.to_pylist())

    def gather(left: pa.Table, right: pa.Table) -> pa.Table:
        _, c, totals = counted_chunk(left, right)
        cells, n = _histogram(c, totals, train_docs, train_tokens)
        return pa.table([cells, n], ["cell", "n"])

    def apply(left: pa.Table, right: pa.Table) -> pa.Table:
        row, c, totals = counted_chunk(left, right)
        ids = pa.ipc.open_stream(row["ids"]).read_all().column(0).combine_chunks()
        return pa.table([ids, pa.array(c.counted), *(pa.array(x) for x in _scores(c, totals, weights, train_docs, train_tokens, vocabulary))], ["doc_id", "counted", *(x.split()[0] for x in SCORES.split(", "))])

    both = chunks.groupBy("chunk").cogroup(replies.groupBy("sender"))
    # at most BUCKETS * GRID**3 cells, whatever the corpus
    found = both.applyInArrow(gather, "cell bigint, n bigint").groupBy("cell").agg(F.sum("n").alias("n")).orderBy("cell").toArrow()
    weights = estimate(found.column("cell").to_numpy(), found.column("n").to_numpy(), vocabulary)
    return both.applyInArrow(apply, f"doc_id {kind}, counted boolean, {SCORES}")
