"""Language-model scores by context-tree weighting over bytes, beside a smoothed unigram over words.

A byte is eight binary decisions (255 inner nodes of its tree); each decision has, for every context of 0 to 3 bytes before it (the
tree's depth), a Krichevsky-Trofimov estimate from the training counts. Bottom up, each context weighs its own estimate against the
product of its longer contexts; the weights then turn into one table of byte probabilities for each context, so that scoring is a
look-up. The tables of the most frequent contexts go to all tasks; bytes after any other context meet its table in a join.
"""

from __future__ import annotations

import uuid
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_texts, give_back, per_worker, pick, release, written
from .shingles import word_hashes

#: Words whose counts all tasks are given (the most frequent); the others' counts are joined.
HEAD_WORDS = 100_000
#: Three-byte contexts whose tables (1 KB each) all tasks are given, the most frequent first; the others' are joined. Shorter contexts number 2^16 + 2^8 at most.
HEAD_CONTEXTS = 65_536
#: Words end at blanks, so no word has this hash but by chance; it stands for the end of a text.
END_KEY = -1
CHUNK = 400_000
#: Words (and half the bytes) that a task gathers before it counts them and hands the counts on.
GATHERED = 2_500_000
OTHER, UNSEEN2, ROOT = 1 << 24, 1 << 25, 1 << 26
_BYTES = np.arange(256)


def grams(raws: list[bytes]) -> tuple[np.ndarray, np.ndarray]:
    """Of each byte of the lower-cased texts, and of the zero that ends each: the three bytes before and itself as one number; and where each text begins (one entry more)."""
    codes = np.frombuffer(b"\0\0\0" + b"".join(r.lower() + b"\0\0\0" for r in raws), np.uint8).astype(np.uint32)
    keys = (codes[:-3] << np.uint32(24)) | (codes[1:-2] << np.uint32(16)) | (codes[2:-1] << np.uint32(8)) | codes[3:]
    sizes = np.fromiter(map(len, raws), np.int64, len(raws))
    ends = np.cumsum(sizes + 3)
    scored = np.ones(len(keys), bool)
    scored[ends - 1] = scored[ends - 2] = False
    return keys[scored], np.concatenate([[0], np.cumsum(sizes + 1)])


def chunks(raws: list[bytes]) -> Iterator[list[bytes]]:
    held, size = [], 0
    for r in raws:
        held.append(r)
        size += len(r)
        if size > CHUNK:
            yield held
            held, size = [], 0
    if held:
        yield held


def _gather(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
    """Counts of word hashes (kind 0) and of byte grams (kind 1), summed over stretches of the partition."""

    def out(kind: int, parts: list[np.ndarray], signed) -> pa.RecordBatch:
        keys, n = np.unique(np.concatenate(parts), return_counts=True)
        return pa.RecordBatch.from_arrays([pa.array(np.full(len(keys), kind, np.int32)), pa.array(keys.view(np.int64) if signed else keys.astype(np.int64)), pa.array(n.astype(np.int64))], ["kind", "key", "n"])

    release()  # a model of an earlier stage that this worker still holds
    words, bytes_, texts = [], [], 0
    for batch in batches:
        for raws in chunks(byte_texts(batch.column(0))):
            words.append(word_hashes(raws)[0])
            bytes_.append(grams(raws)[0])
            texts += len(raws)
            if sum(map(len, words)) > GATHERED:
                yield out(0, words, True)
                words = []
            if sum(map(len, bytes_)) > 2 * GATHERED:
                yield out(1, bytes_, False)
                bytes_ = []
    if words:
        yield out(0, words, True)
    if bytes_:
        yield out(1, bytes_, False)
    if texts:
        give_back()
        yield pa.RecordBatch.from_arrays([pa.array([0], pa.int32()), pa.array([END_KEY], pa.int64()), pa.array([texts], pa.int64())], ["kind", "key", "n"])


def log_gamma(x: np.ndarray) -> np.ndarray:
    """Stirling's series, after a shift by eight."""
    shift = np.ones_like(x)
    for i in range(8):
        shift = shift * (x + i)
    y = x + 8
    return (y - 0.5) * np.log(y) - y + 0.5 * np.log(2 * np.pi) + 1 / (12 * y) - 1 / (360 * y**3) + 1 / (1260 * y**5) - np.log(shift)


def decisions(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Zeros and ones at the 255 inner nodes (in heap order) from byte counts [contexts, 256]."""
    zeros, ones = [], []
    for j in range(8):
        halves = counts.reshape(len(counts), 1 << j, 2, 1 << (7 - j)).sum(-1)
        zeros.append(halves[:, :, 0])
        ones.append(halves[:, :, 1])
    return np.concatenate(zeros, 1).astype(float), np.concatenate(ones, 1).astype(float)


def estimate(counts: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Log of the estimator's block probability, and its probability that the next decision is 1."""
    a, b = decisions(counts)
    return log_gamma(a + 0.5) + log_gamma(b + 0.5) - log_gamma(a + b + 1) - np.log(np.pi), (b + 0.5) / (a + b + 1)


def weigh(block: np.ndarray, below: np.ndarray) -> tuple[np.ndarray, np.ndarray]:
    """Log of the weighted block probability of half the estimator's and half the longer contexts' product; and the estimator's share of it."""
    whole = np.logaddexp(block, below) - np.log(2)
    return whole, np.exp(block - np.log(2) - whole)


def sums(values: np.ndarray, owner: np.ndarray, n: int) -> np.ndarray:
    out = np.zeros((n, values.shape[1]), values.dtype)
    np.add.at(out, owner, values)
    return out


def pair(context: np.ndarray, byte: np.ndarray, n: np.ndarray):
    """The contexts that end in the same two bytes: (three-byte contexts, their counts, their decisions mixed from two bytes on, the same for an unseen
    third byte; log of the weighted block probability and byte counts of the two bytes' context)."""
    three, at = np.unique(context, return_inverse=True)
    counts3 = np.zeros((len(three), 256), np.int64)
    np.add.at(counts3, (at, byte), n)
    block3, kt3 = estimate(counts3)
    counts2 = counts3.sum(0, keepdims=True)
    block2, kt2 = estimate(counts2)
    whole2, own2 = weigh(block2, block3.sum(0, keepdims=True))
    return three, counts3.sum(1), own2 * kt2 + (1 - own2) * kt3, (own2 * kt2 + (1 - own2) * 0.5)[0], whole2[0], counts2[0]


def single(whole2: np.ndarray, counts2: np.ndarray):
    """The context of one byte from those of two: its share, its decisions, its log weighted block probability, its byte counts."""
    counts1 = counts2.sum(0, keepdims=True)
    block1, kt1 = estimate(counts1)
    whole1, own1 = weigh(block1, whole2.sum(0, keepdims=True))
    return own1[0], kt1[0], whole1[0], counts1[0]


def subtree(context: np.ndarray, byte: np.ndarray, n: np.ndarray):
    """All contexts that end in one byte: rows (context id, decisions' probabilities under contexts of 1 to 3 bytes), and what the root needs."""
    two = context & 0xFFFF
    parts = [(int(t), pair(context[two == t], byte[two == t], n[two == t])) for t in np.unique(two)]
    own1, kt1, whole1, counts1 = single(np.array([x[4] for _, x in parts]), np.array([x[5] for _, x in parts]))
    rows = [(c, own1 * kt1 + (1 - own1) * v) for t, x in parts for c, v in [*zip(x[0].tolist(), x[2]), (OTHER | t, x[3])]]
    return [*rows, (UNSEEN2 | int(context[0] & 255), own1 * kt1 + (1 - own1) * 0.5)], whole1, counts1


def _pairs(key, table):
    three, n, deep, other, whole, counts = pair(*(table.column(c).to_numpy() for c in ("context", "byte", "n")))
    two = key[0].as_py()
    return pa.table({
        "context": pa.array([*three.tolist(), OTHER | two, ROOT | two], pa.int64()), "n": pa.array([*n.tolist(), 0, 0], pa.int64()),
        "values": pa.array([*(r.tobytes() for r in deep.astype("<f4")), other.astype("<f4").tobytes(), whole.astype("<f8").tobytes()], pa.binary()),
        "counts": pa.array([None] * (len(three) + 1) + [counts.astype("<i8").tobytes()], pa.binary()),
    })


def _singles(key, table):
    arrays = (np.frombuffer(b"".join(table.column(c).to_pylist()), t).reshape(-1, w) for c, t, w in (("values", "<f8", 255), ("counts", "<i8", 256)))
    own, kt, whole, counts = single(*arrays)
    return pa.table({"last": [key[0].as_py()], "own": [own.tobytes()], "kt": [kt.tobytes()], "whole": [whole.tobytes()], "counts": [counts.astype("<i8").tobytes()]}, pa.schema([("last", pa.int64()), *((c, pa.binary()) for c in ("own", "kt", "whole", "counts"))]))


def byte_logs(p: np.ndarray) -> np.ndarray:
    """log10 probabilities of the 256 bytes from the decisions' probabilities of 1, [rows, 255]."""
    out = np.zeros((len(p), 256), np.float32)
    one, zero = np.log10(p), np.log10(1 - p)
    for j in range(8):
        node = (1 << j) + (_BYTES >> (8 - j)) - 1
        out += np.where(((_BYTES >> (7 - j)) & 1) == 1, one[:, node], zero[:, node])
    return out


def _root(roots: list[tuple[int, np.ndarray, np.ndarray]]) -> tuple[np.ndarray, np.ndarray]:
    """Share and decisions of the empty context."""
    if not roots:
        return np.full((1, 255), 0.5), np.full((1, 255), 0.5)
    block0, kt0 = estimate(np.sum([c for _, _, c in roots], 0)[None])
    return weigh(block0, np.sum([w for _, w, _ in roots], 0)[None])[1], kt0


class ByteModel:
    """Tables of log10 byte probabilities and the row of each three-byte context."""

    def __init__(self, contexts: np.ndarray, values: np.ndarray, roots: list[tuple[int, np.ndarray, np.ndarray]]):
        own0, kt0 = _root(roots)
        parts = [byte_logs(own0 * kt0 + (1 - own0) * v) for v in np.array_split(values, max(1, len(values) // 4096))] if len(values) else []
        self.logs = np.concatenate([*parts, byte_logs(own0 * kt0 + (1 - own0) * 0.5)]).astype(np.float32)
        row = np.full((256, 256, 256), len(self.logs) - 1, np.int32)
        order = np.argsort(-contexts, kind="stable")  # the less is known of a context, the larger its id: the known ones overwrite
        for c, r in zip(contexts[order].tolist(), order.tolist()):
            if c >= UNSEEN2:
                row[:, :, c & 255] = r
            elif c >= OTHER:
                row[:, (c >> 8) & 255, c & 255] = r
            else:
                row[c >> 16, (c >> 8) & 255, c & 255] = r
        self.row = row.ravel()
        self.deep = np.append(contexts < OTHER, False)

    def scores(self, raws: list[bytes]) -> np.ndarray:
        return self.split_scores(raws, False)[0]

    def split_scores(self, raws: list[bytes], apart: bool = True):
        """Sums for each text; with `apart`, of the bytes after known three-byte contexts alone, and (text, gram, log10 probability under shorter contexts) of the others."""
        keys, bounds = grams(raws)
        row = self.row[keys >> np.uint32(8)].astype(np.int64)
        logs = self.logs.ravel()[row * 256 + (keys & np.uint32(255))].astype(np.float64)
        if not apart:
            return np.add.reduceat(logs, bounds[:-1]), None
        rest = np.flatnonzero(~self.deep[row])
        left = (np.searchsorted(bounds, rest, "right") - 1, keys[rest].astype(np.int64), logs[rest])
        logs[rest] = 0
        return np.add.reduceat(logs, bounds[:-1]), left


class ContextTables:
    """The trained contexts: a stored table (context, n, values), and 256 rows at most for the contexts of one byte, which the driver holds.

    No task holds more than the contexts that end in the same two bytes."""

    def __init__(self, counts: DataFrame):
        summed = counts.select(F.shiftright("key", 8).alias("context"), F.col("key").bitwiseAND(255).alias("byte"), "n").groupBy("context", "byte").agg(F.sum("n").alias("n"))
        found = written(summed.groupBy(F.col("context").bitwiseAND(0xFFFF).alias("two")).applyInArrow(_pairs, "context long, n long, values binary, counts binary"))
        self.table = found.where(F.col("context") < ROOT).drop("counts")
        ends = found.where(F.col("context") >= ROOT).groupBy(F.col("context").bitwiseAND(255).alias("last")).applyInArrow(_singles, "last long, own binary, kt binary, whole binary, counts binary").collect()
        self.own, self.kt = np.full((256, 255), 0.5), np.full((256, 255), 0.5)
        for r in ends:
            self.own[r["last"]], self.kt[r["last"]] = np.frombuffer(r["own"]), np.frombuffer(r["kt"])
        self.lasts = sorted(r["last"] for r in ends)
        self.roots = [(r["last"], np.frombuffer(r["whole"]), np.frombuffer(r["counts"], "<i8")) for r in ends]

    def under(self, context: np.ndarray, deeper: np.ndarray) -> np.ndarray:
        """Decisions from one byte on."""
        own, kt = self.own[context & 255], self.kt[context & 255]
        return own * kt + (1 - own) * deeper

    def head(self, most: int | None) -> tuple[np.ndarray, np.ndarray, list]:
        """What ByteModel takes: of the three-byte contexts the `most` most frequent (all of them without a number), and all shorter ones."""
        deep = self.table.where(F.col("context") < OTHER)
        rows = (deep if most is None else deep.orderBy(F.desc("n"), "context").limit(most)).union(self.table.where(F.col("context") >= OTHER)).select("context", "values").toArrow()
        context = np.concatenate([rows.column("context").to_numpy(), np.array([UNSEEN2 | x for x in self.lasts], np.int64)])
        raw = b"".join(rows.column("values").to_pylist())
        values = np.concatenate([np.frombuffer(raw, "<f4").reshape(-1, 255), np.full((len(self.lasts), 255), 0.5, np.float32)])
        parts = np.array_split(np.arange(len(context)), len(context) // 4096 + 1)
        return context, np.concatenate([self.under(context[p], values[p]).astype(np.float32) for p in parts]), self.roots

    def tail(self, most: int) -> DataFrame | None:
        """(context, logs): tables of the three-byte contexts beyond the `most` most frequent, if there are any."""
        deep = self.table.where(F.col("context") < OTHER)
        if deep.count() <= most:
            return None
        edge = deep.select("n", "context").orderBy(F.desc("n"), "context").limit(most).orderBy("n", F.desc("context")).first()
        shared = self.table.sparkSession.sparkContext.broadcast((self.own, self.kt, *_root(self.roots)))

        def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            own, kt, own0, kt0 = shared.value
            for batch in batches:
                for at in range(0, batch.num_rows, 1024):
                    part = batch.slice(at, 1024)
                    last = part.column(0).to_numpy() & 255
                    deeper = np.frombuffer(b"".join(part.column(1).to_pylist()), "<f4").reshape(-1, 255)
                    logs = byte_logs(own0 * kt0 + (1 - own0) * (own[last] * kt[last] + (1 - own[last]) * deeper))
                    yield pa.RecordBatch.from_arrays([part.column(0), pa.ListArray.from_arrays(pa.array(np.arange(len(last) + 1, dtype=np.int32) * 256), pa.array(logs.ravel()))], ["context", "logs"])

        rest = deep.where((F.col("n") < edge.n) | ((F.col("n") == edge.n) & (F.col("context") > edge.context)))
        return written(rest.select("context", "values").mapInArrow(run, "context long, logs array<float>"))


def train_bytes(counts: DataFrame) -> tuple[np.ndarray, np.ndarray, list]:
    """The model's rows of all contexts from gram counts (key, n): for corpora whose contexts are few."""
    return ContextTables(counts).head(None)


def score_documents(docs: DataFrame, head_words: int = HEAD_WORDS, head_contexts: int = HEAD_CONTEXTS) -> DataFrame:
    """(doc_id, held_out, n_tokens, n_known, train_tokens, base_score, score) of each row.

    Rows whose crc32(doc_id as text) mod 10 is 0 are held out; a null doc_id trains. Texts are lower-cased (A-Z); null counts as
    empty, which has the end token alone. score: log10 probability of the text's bytes and its end. Repeated rows count and come
    out as often as they occur; an empty table gives no rows; without training rows every decision is even. Words are told apart
    by 64 bits of a hash.
    """
    spark = docs.sparkSession
    held_out = F.coalesce(F.crc32(F.col("doc_id").cast("string").cast("binary")) % 10 == 0, F.lit(False))
    table = pick(docs, "doc_id", "text").select("doc_id", held_out.alias("held_out"), "text")
    gathered = written(table.where("not held_out").select("text").mapInArrow(_gather, "kind int, key long, n long").groupBy("kind", "key").agg(F.sum("n").alias("n")))
    counts = gathered.where("kind = 0").select("key", "n")
    total, distinct = counts.agg(F.coalesce(F.sum("n"), F.lit(0)), F.count("*")).first()
    divisor = float(np.log10(total + 0.1 * (distinct + 1)))
    head = counts.orderBy(F.desc("n"), "key").limit(head_words).toArrow().sort_by("key")
    contexts = ContextTables(gathered.where("kind = 1").select("key", "n"))
    deeper = contexts.tail(head_contexts)
    shared = spark.sparkContext.broadcast((head.column("key").to_numpy(), head.column("n").to_numpy(), *contexts.head(head_contexts)))
    token, apart = uuid.uuid4().hex, deeper is not None

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        def build():
            key, n, *model = shared.value
            return np.append(key, 2**63 - 1), np.append(n, 0), np.append(np.log10(n + 0.1), 0.0), ByteModel(*model)

        key, n, logs, model = per_worker(token, build)
        for batch in batches:
            at = 0
            for raws in chunks(byte_texts(batch.column(2))):
                words, bounds = word_hashes(raws)
                hashes = words.view(np.int64)
                # The end token is inserted after each text's words.
                hashes = np.insert(hashes, bounds[1:], END_KEY)
                owner = np.repeat(np.arange(len(raws)), np.diff(bounds) + 1)
                place = np.searchsorted(key, hashes)
                known = key[place] == hashes
                sums = np.bincount(owner[known], logs[place[known]], len(raws))
                tail, tail_owner = hashes[~known], owner[~known]
                cuts = np.searchsorted(tail_owner, np.arange(len(raws) + 1))
                score, left = model.split_scores(raws, apart)
                near = np.searchsorted(left[0], np.arange(len(raws) + 1)) if apart else np.zeros(len(raws) + 1)
                bytes_, logs_ = (left[1], left[2]) if apart else (np.zeros(0, np.int64), np.zeros(0))
                near = pa.array(near.astype(np.int32))
                yield pa.RecordBatch.from_arrays([
                    batch.column(0).slice(at, len(raws)), batch.column(1).slice(at, len(raws)), pa.array(np.diff(bounds) + 1), pa.array(np.bincount(owner[known], n[place[known]] > 0, len(raws)).astype(np.int64)),
                    pa.array(sums), pa.ListArray.from_arrays(pa.array(cuts.astype(np.int32)), pa.array(tail)), pa.array(score),
                    pa.ListArray.from_arrays(near, pa.array(bytes_)), pa.ListArray.from_arrays(near, pa.array(logs_)),
                ], ["doc_id", "held_out", "n_tokens", "head_known", "head_sum", "tail", "score", "grams", "logs"])
                at += len(raws)

    scored = written(table.mapInArrow(run, "doc_id long, held_out boolean, n_tokens long, head_known long, head_sum double, tail array<long>, score double, grams array<long>, logs array<double>").withColumn("row", F.monotonically_increasing_id()))
    rest = (
        scored.select("row", F.explode("tail").alias("key")).join(counts, "key", "left")
        .groupBy("row").agg(F.sum(F.log10(F.coalesce("n", F.lit(0)) + F.lit(0.1))).alias("tail_sum"), F.count("n").alias("tail_known"))
    )
    whole = scored.drop("tail", "grams", "logs").join(rest, "row", "left")
    if apart:
        missed = scored.select("row", F.explode(F.arrays_zip("grams", "logs")).alias("g")).select("row", F.shiftright("g.grams", 8).alias("context"), F.col("g.grams").bitwiseAND(255).cast("int").alias("byte"), F.col("g.logs").alias("log"))
        counted = missed.groupBy("row", "context", "byte").agg(F.count("*").alias("m"), F.first("log").alias("log"))  # before the shuffle by context
        more = counted.join(deeper, "context", "left").groupBy("row").agg(F.sum(F.col("m") * F.coalesce(F.element_at("logs", F.col("byte") + 1).cast("double"), "log")).alias("more"))
        whole = whole.join(more, "row", "left").withColumn("score", F.col("score") + F.coalesce("more", F.lit(0.0)))
    return whole.select(
        "doc_id", "held_out", "n_tokens", (F.col("head_known") + F.coalesce("tail_known", F.lit(0))).alias("n_known"), F.lit(total).cast("long").alias("train_tokens"),
        (F.col("head_sum") + F.coalesce("tail_sum", F.lit(0.0)) - F.col("n_tokens") * F.lit(divisor)).alias("base_score"), "score",
    )
