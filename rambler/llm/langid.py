"""Language identification by unigram piece models whose segmentations are summed out.

For each language the pieces of a fixed public vocabulary have probabilities, fitted by expectation-maximisation on a bounded
sample of labelled documents, of which all words count. The probability of a run of letters is the sum over all its segmentations
into pieces of any length, found by the forward algorithm; a text's is the product over its runs. Scores of words are remembered by
each worker.
"""

from __future__ import annotations

import uuid
from collections import Counter
from collections.abc import Iterable, Iterator

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from .common import byte_texts, per_worker, pick, without

UNKNOWN = "und"
#: Characters up to which probabilities are summed as they are; sums over longer runs are made of logs, so that they don't vanish.
PLAIN_CHARS = 40
#: Runs that are taken at once, by their number times the longest's length.
LATTICE_CELLS = 150_000
#: Words that a worker remembers, and their bytes. Only speed depends on it.
CACHE_ENTRIES, CACHE_BYTES = 400_000, 16_000_000
_LETTERS = bytes(b if b >= 128 or 65 <= b <= 90 or 97 <= b <= 122 else 32 for b in range(256))
_RUNS = regex.compile(r"\p{L}+").findall


def default_vocab() -> str:
    import public_tokenizers

    return public_tokenizers.path("piece_bpe_32k.model")


def load_pieces(path: str) -> dict[str, int]:
    """Lower-cased letter pieces of a sentencepiece model, with its word-begin mark."""
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=path)
    found = dict.fromkeys(p for i in range(model.get_piece_size()) if not (model.is_control(i) or model.is_unknown(i) or model.is_byte(i)) and ((p := model.id_to_piece(i).lower()).lstrip("▁").isalpha() or p == "▁") and "▁" not in p[1:])
    return {p: i for i, p in enumerate(found)}


def beginnings(pieces: dict[str, int]) -> dict[str, int]:
    """Numbers of the pieces, and -1 for what pieces only begin with: where neither stands, no longer piece can follow."""
    return {p[:i]: -1 for p in pieces for i in range(1, len(p))} | pieces


def stretches(word: bytes) -> list[str]:
    """Lower-cased letter runs of a raw word, each whole and marked as a word's begin."""
    return [f"▁{run}" for run in _RUNS(word.decode("utf-8", "replace").lower())]


def raw_words(raw: bytes) -> list[bytes]:
    """Pieces of a text between ASCII characters that aren't letters."""
    return raw.translate(_LETTERS).split()


class Lattice:
    """All segmentations of many stretches: edges (stretch, start, end, piece), grouped by their end."""

    def __init__(self, texts: list[str], pieces: dict[str, int], known: dict[str, int] | None = None):
        self.lengths = np.fromiter(map(len, texts), np.int64, len(texts))
        find, unknown, owner, start, end, piece = (known or beginnings(pieces)).get, len(pieces), [], [], [], []
        for w, t in enumerate(texts):
            n = len(t)
            for i in range(n):
                j = i + 1
                p = find(t[i:j])
                if p is None or p < 0:  # the character alone is no piece, but it may begin one
                    owner.append(w)
                    start.append(i)
                    end.append(j)
                    piece.append(unknown)
                while p is not None:
                    if p >= 0:
                        owner.append(w)
                        start.append(i)
                        end.append(j)
                        piece.append(p)
                    if j == n:
                        break
                    j += 1
                    p = find(t[i:j])
        self.owner, self.start, self.end, self.piece = (np.array(x, np.int32) for x in (owner, start, end, piece))
        width = int(self.lengths.max(initial=0)) + 1
        self.by_end, self.by_start = ([order[a:b] for order in [np.argsort(x, kind="stable")] for cuts in [np.searchsorted(x[order], np.arange(width + 1)).tolist()] for a, b in zip(cuts[:-1], cuts[1:])] for x in (self.end, self.start))

    def forward_logs(self, prob: np.ndarray) -> np.ndarray:
        """forward() in logs, for stretches so long that probabilities would vanish."""
        alpha = np.full((len(self.lengths), len(self.by_end), prob.shape[1]), -np.inf)
        alpha[:, 0] = 0
        logs = np.log(prob)
        for e, at in enumerate(self.by_end):
            if at.size:
                owner = self.owner[at]
                first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
                alpha[owner[first], e] = np.logaddexp.reduceat(alpha[owner, self.start[at]] + logs[self.piece[at]], first)
        return alpha

    def forward(self, prob: np.ndarray) -> np.ndarray:
        """alpha[stretch, position, language] for prob[piece, language]."""
        alpha = np.zeros((len(self.lengths), len(self.by_end), prob.shape[1]))
        alpha[:, 0] = 1
        for e, at in enumerate(self.by_end):
            if at.size:
                owner = self.owner[at]  # rising, as stretches were added in turn
                first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
                alpha[owner[first], e] += np.add.reduceat(alpha[owner, self.start[at]] * prob[self.piece[at]], first)
        return alpha

    def likelihoods(self, prob: np.ndarray) -> np.ndarray:
        at = np.arange(len(self.lengths)), self.lengths
        return np.log(self.forward(prob)[at]) if self.lengths.max(initial=0) <= PLAIN_CHARS else self.forward_logs(prob)[at]

    def expected(self, prob: np.ndarray, weight: np.ndarray) -> np.ndarray:
        """Expected piece counts under one language's probabilities."""
        if self.lengths.max(initial=0) > PLAIN_CHARS:
            return self._expected_logs(prob, weight)
        p = prob[:, None]
        alpha = self.forward(p)[:, :, 0]
        beta = np.zeros_like(alpha)
        beta[np.arange(len(self.lengths)), self.lengths] = 1
        for s in range(len(self.by_start) - 1, -1, -1):
            at = self.by_start[s]
            if at.size:
                owner = self.owner[at]
                first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
                beta[owner[first], s] += np.add.reduceat(prob[self.piece[at]] * beta[owner, self.end[at]], first)
        total = alpha[np.arange(len(self.lengths)), self.lengths]
        share = alpha[self.owner, self.start] * prob[self.piece] * beta[self.owner, self.end] / total[self.owner] * weight[self.owner]
        return np.bincount(self.piece, share, len(prob))


    def _expected_logs(self, prob: np.ndarray, weight: np.ndarray) -> np.ndarray:
        logs, end = np.log(prob), (np.arange(len(self.lengths)), self.lengths)
        alpha = self.forward_logs(prob[:, None])[:, :, 0]
        beta = np.full_like(alpha, -np.inf)
        beta[end] = 0
        for s in range(len(self.by_start) - 1, -1, -1):
            at = self.by_start[s]
            if at.size:
                owner = self.owner[at]
                first = np.flatnonzero(np.r_[True, owner[1:] != owner[:-1]])
                beta[owner[first], s] = np.logaddexp.reduceat(logs[self.piece[at]] + beta[owner, self.end[at]], first)
        share = np.exp(alpha[self.owner, self.start] + logs[self.piece] + beta[self.owner, self.end] - alpha[end][self.owner]) * weight[self.owner]
        return np.bincount(self.piece, share, len(prob))


def bounded(texts: list[str]) -> Iterator[np.ndarray]:
    """Places of the stretches in bundles of like length, each of LATTICE_CELLS cells at most or a single stretch."""
    lengths = np.fromiter(map(len, texts), np.int64, len(texts))
    order = np.argsort(lengths, kind="stable")
    a = 0
    while a < len(order):
        b = a + 1
        step = max(1, LATTICE_CELLS // int(lengths[order[a]] + 1))
        b = min(len(order), a + step)
        while b > a + 1 and ((b - a) * (lengths[order[b - 1]] + 1) > LATTICE_CELLS or (lengths[order[b - 1]] > PLAIN_CHARS) != (lengths[order[a]] > PLAIN_CHARS)):
            b = a + (b - a) // 2
        yield np.sort(order[a:b])
        a = b


def fit(counts: dict[str, Counter], pieces: dict[str, int], rounds: int = 3, smooth: float = 0.1) -> tuple[list[str], np.ndarray]:
    """Languages, sorted, and prob[piece, language]; the last row is for a character that the vocabulary lacks."""
    langs = sorted(counts)
    prob, known = np.full((len(pieces) + 1, len(langs)), 1e-6), beginnings(pieces)
    for k, lang in enumerate(langs):
        spread = Counter()
        for word, n in counts[lang].items():
            for t in stretches(word):
                spread[t] += n
        texts, weight = list(spread), np.fromiter(spread.values(), float, len(spread))
        p = np.full(len(pieces) + 1, 1 / (len(pieces) + 1))
        if texts:
            lattices = [(Lattice([texts[i] for i in at.tolist()], pieces, known), weight[at]) for at in bounded(texts)]
            for _ in range(rounds):
                got = sum(lattice.expected(p, n) for lattice, n in lattices)[:-1] + smooth
                p[:-1] = got / got.sum()
                p[-1] = 1e-6
        prob[:, k] = p
        prob[-1, k] = 1e-6
    return langs, prob


def sample_counts(docs: DataFrame, sample_docs: int) -> dict[str, Counter]:
    """Word counts by language of about `sample_docs` labelled documents a language, taken by a hash of the id: all words of those documents."""
    sizes = {r.lang: r.n for r in docs.groupBy("lang").agg(F.count("*").alias("n")).collect()}
    if not sizes:
        return {}
    share = F.create_map(*[x for k, n in sizes.items() for x in (F.lit(k), F.lit(min(1.0, sample_docs / n)))])
    chosen = docs.where((F.pmod(F.xxhash64(F.lit(7), "doc_id"), F.lit(1_000_003)) / 1_000_003.0) < F.element_at(share, F.col("lang")))

    def run(batches):
        for batch in batches:
            found: dict[str, Counter] = {}
            for lang, raw in zip(batch.column(0).to_pylist(), byte_texts(batch.column(1))):
                found.setdefault(lang, Counter()).update(raw_words(raw))
            rows = [(lang, w, n) for lang, c in found.items() for w, n in c.items()]
            yield pa.RecordBatch.from_arrays([pa.array(c, t) for c, t in zip(zip(*rows) if rows else ((), (), ()), (pa.string(), pa.binary(), pa.int64()))], ["lang", "word", "n"])

    words = chosen.select("lang", "text").mapInArrow(run, "lang string, word binary, n long").groupBy("lang", "word").agg(F.sum("n").alias("n"))
    out: dict[str, Counter] = {lang: Counter() for lang in sizes}
    for batch in words.toArrow().to_batches():
        for lang, word, n in zip(*(c.to_pylist() for c in batch.columns)):
            out[lang][word] = n
    return out


class Scorer:
    """Log probabilities of words in all languages, remembered as rows of a growing table."""

    def __init__(self, langs: list[str], prob: np.ndarray, pieces: dict[str, int]):
        self.langs, self.prob, self.pieces = langs, prob, pieces
        self.known = beginnings(pieces)
        self.rows: dict[bytes, int] = {}
        self.size = 0
        self.table = np.zeros((1024, len(langs) + 1))  # the last column: stretches of letters in the word

    def _learn(self, words: list[bytes]) -> None:
        size = sum(map(len, words))
        if self._full(len(words), size):
            self.rows.clear()
            self.size = 0
        self.size += size
        parts = [stretches(w) for w in words]
        flat = [t for p in parts for t in p]
        score = np.zeros((len(flat), len(self.langs)))
        for at in bounded(flat):
            score[at] = Lattice([flat[i] for i in at.tolist()], self.pieces, self.known).likelihoods(self.prob)
        base = len(self.rows)
        while base + len(words) > len(self.table):
            self.table = np.concatenate([self.table, np.zeros_like(self.table)])
        owner = np.repeat(np.arange(len(words)), [len(p) for p in parts])
        block = np.zeros((len(words), len(self.langs) + 1))
        np.add.at(block[:, :-1], owner, score)
        block[:, -1] = np.bincount(owner, minlength=len(words))
        self.table[base : base + len(words)] = block
        self.rows.update(zip(words, range(base, base + len(words))))

    def _full(self, words: int, size: int) -> bool:
        return len(self.rows) + words > CACHE_ENTRIES or self.size + size > CACHE_BYTES

    def score(self, raws: list[bytes]) -> np.ndarray:
        """Sums over each text's words: a column for each language, and the number of letter stretches."""
        out = np.zeros((len(raws), len(self.langs) + 1))
        todo: list[tuple[int, list[bytes]]] = []
        new: dict[bytes, None] = {}

        def settle():
            if new:
                if self._full(len(new), sum(map(len, new))):  # the cache starts anew: all words of the waiting texts are needed
                    new.update(dict.fromkeys(w for _, words in todo for w in words))
                self._learn(list(new))
                new.clear()
            for i, words in todo:
                out[i] += self.table[np.fromiter(map(self.rows.__getitem__, words), np.int64, len(words))].sum(0)
            todo.clear()

        for i, raw in enumerate(raws):
            words = raw_words(raw)
            for at in range(0, len(words), 100_000):  # very long texts are taken in stretches
                part = words[at : at + 100_000]
                todo.append((i, part))
                new.update(dict.fromkeys(w for w in set(part) if w not in self.rows))
                if len(new) > 20_000 or len(todo) > 2_000:
                    settle()
        settle()
        return out


def identify(docs: DataFrame, train: DataFrame, vocab: str | None = None, sample_docs: int = 500) -> DataFrame:
    """All columns of `docs` with lang_pred and score (0 to 1, the winner's share of the tempered posterior) added.

    train: labelled rows (doc_id, text, lang); about `sample_docs` of them a language fit the model, with all their words: this bounds
    what the driver holds. Predictions use the text alone. A null text, or one without a letter, is 'und' with score 0; so is every
    text if there is no labelled row. Ties go to the language first in order. An empty table gives no rows, repeated rows one each;
    other columns pass through, but a column of `docs` named lang_pred or score (in any case) gives way to the new one.
    """
    labelled = pick(train, "doc_id", "text", "lang").where("lang is not null and text is not null")
    docs = without(docs, "lang_pred", "score")
    pieces = load_pieces(vocab or default_vocab())
    model = docs.sparkSession.sparkContext.broadcast((*fit(sample_counts(labelled, sample_docs), pieces), pieces))
    token = uuid.uuid4().hex
    names = docs.columns
    at = names.index("text")
    fields = ", ".join(f"_{i} {t}" for i, (_, t) in enumerate(docs.dtypes))

    def run(batches: Iterable[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        scorer = per_worker(token, lambda: Scorer(*model.value))
        for batch in batches:
            sums = scorer.score(byte_texts(batch.column(at)))
            letters, logs = sums[:, -1], sums[:, :-1]
            if scorer.langs:
                # Long texts would all give 1: the evidence counts as that of 8 words at most.
                tempered = (logs - logs.max(1, keepdims=True)) * np.minimum(1, 8 / np.maximum(letters, 1))[:, None]
                share = np.exp(tempered)
                share /= share.sum(1, keepdims=True)
                best = logs.argmax(1)
                pred = [scorer.langs[b] if n else UNKNOWN for b, n in zip(best.tolist(), letters.tolist())]
                score = np.where(letters > 0, share[np.arange(len(best)), best], 0.0)
            else:
                pred, score = [UNKNOWN] * len(sums), np.zeros(len(sums))
            columns = [batch.column(i) for i in range(len(names))]
            yield pa.RecordBatch.from_arrays([*columns, pa.array(pred, pa.string()), pa.array(score)], [f"_{i}" for i in range(len(names))] + ["lang_pred", "score"])

    numbered = docs.toDF(*[f"_{i}" for i in range(len(names))])
    return numbered.mapInArrow(run, f"{fields}, lang_pred string, score double").toDF(*names, "lang_pred", "score")
