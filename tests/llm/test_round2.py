"""Large groups, bounds that are exceeded, stored filters, prefixes, and odd tables."""

import random
import re

import numpy as np
import pyarrow as pa
import pytest

from rambler.llm import bpe, decontam, jaccard, langid, licenses, linededup, lm, tokencount
from rambler.llm.queries import QUERIES


def docs_of(spark, rows):
    return spark.createDataFrame(rows, "doc_id long, text string")


def shingles(text):
    w = re.findall(r"[^\x20\x09-\x0D]+", text or "")
    return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()


def classes(rows):
    """By brute force: the least id that links reach, for each row."""
    sets = [shingles(t) for _, t in rows]
    comp = list(range(len(rows)))

    def root(i):
        while comp[i] != i:
            i = comp[i]
        return i

    for a in range(len(rows)):
        for b in range(a):
            if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                comp[root(a)] = root(b)
    groups = {}
    for i in range(len(rows)):
        groups.setdefault(root(i), []).append(rows[i][0])
    least = lambda g: min((x for x in g if x is not None), default=None)
    return sorted(((rows[i][0], len(sets[i]), least(groups[root(i)])) for i in range(len(rows))), key=repr)


def near_copies(n, words=90, seed=2):
    """Edits of one text, most of them near the limit, with a common phrase in all; then unrelated texts that hold the phrase too."""
    rng = np.random.default_rng(seed)
    base = [f"w{i}" for i in range(words)]
    rows = [(0, " ".join(base))]
    for i in range(1, n):
        w = list(base)
        for at in rng.choice(words, rng.integers(1, 5), replace=False):
            w[at] = f"x{rng.integers(0, 30)}" if rng.random() < 0.5 else f"y{i}"
        rows.append((i, " ".join(w)))
    phrase = " ".join(base[20:32])
    return rows + [(n + i, " ".join(f"z{i}_{j}" for j in range(14)) + " " + phrase) for i in range(20)]


@pytest.mark.parametrize("block", [8, 2048])
def test_join_on_a_large_group_of_near_copies(spark, monkeypatch, block):
    """Blocks of the group meet each other; classes are those of brute force, null ids and repeated rows among them."""
    monkeypatch.setattr(jaccard, "BLOCK", block)
    rows = near_copies(100) + [(None, near_copies(3)[1][1]), (5, near_copies(100)[5][1]), (900, None), (901, "")]
    got = sorted(map(tuple, jaccard.jaccard_classes(docs_of(spark, rows)).select("doc_id", "n_shingles", "component_id").collect()), key=repr)
    assert got == classes(rows)


def test_derived_overlaps_are_exact():
    rng = np.random.default_rng(8)
    head = np.sort(rng.choice(10**6, 200, replace=False).astype(np.uint64))
    sets = []
    for i in range(60):
        kept = head[rng.random(200) < rng.choice([0.8, 0.88, 0.95])]
        sets.append(np.union1d(kept, rng.choice(200, rng.integers(0, 40)).astype(np.uint64) + np.uint64(2 * 10**6)))
    linked = [100 * len(np.intersect1d(s, head)) >= 75 * len(np.union1d(s, head)) for s in sets]
    table = pa.table({
        "at": pa.array([0] * 60), "side": pa.array([int(x) for x in linked]), "b": pa.array(range(60)), "n": pa.array([len(s) for s in sets]),
        "kept": pa.array([np.packbits(np.isin(head, s)).tobytes() for s in sets]), "more": pa.array([np.setdiff1d(s, head).tobytes() for s in sets]),
    })
    zero = pa.scalar(0)
    out = jaccard._derived(75)((zero, zero, zero), table)
    label = [-1 if x else i for i, x in enumerate(linked)]
    for a in range(60):
        for b in range(a):
            if not (linked[a] and linked[b]) and 100 * len(np.intersect1d(sets[a], sets[b])) >= 75 * len(np.union1d(sets[a], sets[b])):
                x, y = label[a], label[b]
                label = [y if k == x else k for k in label]
    mine = [-1 if x else i for i, x in enumerate(linked)]
    for a, b in zip(out.column("a").to_pylist(), out.column("b").to_pylist()):
        x, y = mine[a], mine[b]
        mine = [y if k == x else k for k in mine]
    same = lambda ls: {frozenset(i for i, k in enumerate(ls) if k == x) for x in set(ls)}
    assert same(label) == same(mine) and out.num_rows < 60


def test_contexts_beyond_the_bound_are_joined(spark):
    rows = [(i, "".join(chr(97 + (i * 7 + j * j) % 23) for j in range(i % 50))) for i in range(60)] + [(60, None), (3, "again é")]
    whole = sorted(tuple(r) for r in lm.score_documents(docs_of(spark, rows)).select("doc_id", "n_tokens", "score").collect())
    few = sorted(tuple(r) for r in lm.score_documents(docs_of(spark, rows), head_contexts=7).select("doc_id", "n_tokens", "score").collect())
    assert [x[:2] for x in whole] == [x[:2] for x in few]
    assert np.allclose([x[2] for x in whole], [x[2] for x in few], atol=1e-4)
    assert lm.score_documents(docs_of(spark, [])).count() == 0


def test_counts_at_every_prefix():
    from tokenizers import Tokenizer

    counter, library = tokencount.PrefixCounter(bpe.default_vocab()), Tokenizer.from_file(bpe.default_vocab())
    random.seed(4)
    parts = ["a", "12", "\n", " ", "  ", "'re", "'s", "'l", "'", "word", "é", "\t", "!", "<|endoftext|>", "<|end", " ", "中文", "\r\n"]
    for text in ["\n\na12", "it're", *("".join(random.choice(parts) for _ in range(random.randint(0, 9))) for _ in range(300))]:
        counts = counter.prefixes(text)
        assert all(counts[len(text[:i].encode())] == len(library.encode(text[:i], add_special_tokens=False).ids) for i in range(len(text) + 1))
        if (counts <= 3).any():
            assert len(library.encode(counter.cut(text, 3), add_special_tokens=False).ids) <= 3


def test_prefix_table_and_empty_tables(spark):
    got = {r.doc_id: r["counts"] for r in tokencount.prefix_counts(docs_of(spark, [(1, "ab"), (2, None), (3, "ab")])).collect()}
    assert got[1] == got[3] and got[1][0] == 0 and len(got[1]) == 3 and got[2] == [0]
    assert tokencount.count_tokens(docs_of(spark, [])).count() == 0


def test_long_runs_and_long_pieces():
    """Sums over long runs don't vanish; pieces of any length count; logs agree with plain sums."""
    pieces = {"▁": 0, "a": 1, "▁abcdefghijklmnop": 2}
    p = np.array([[0.1], [0.2], [0.3], [1e-6]])
    assert np.exp(langid.Lattice(["▁abcdefghijklmnop"], pieces).likelihoods(p)[0, 0]) == pytest.approx(0.3, rel=1e-6)
    text = "▁" + "a" * 5000
    assert langid.Lattice([text], pieces).likelihoods(p)[0, 0] == pytest.approx(np.log(0.1) + 5000 * np.log(0.2))
    short = langid.Lattice(["▁aaab", "▁ab"], pieces)
    assert np.allclose(np.log(short.forward(p)[[0, 1], [5, 3]]), short.forward_logs(p)[[0, 1], [5, 3]])
    assert np.allclose(short.expected(p[:, 0], np.array([2.0, 1.0])), short._expected_logs(p[:, 0], np.array([2.0, 1.0])))
    many = ["▁" + "a" * n for n in [1, 3, 39, 45, 200_000, 2, 44]]
    bundles = list(langid.bounded(many))
    assert sorted(np.concatenate(bundles).tolist()) == list(range(7))


def test_language_of_odd_tables(spark):
    docs = spark.createDataFrame([(1, "abc", "x", "s"), (1, "abc", "x", "s"), (None, "a" * 3000, "x", "s")], "doc_id long, text string, lang string, Score string")
    got = langid.identify(docs, docs)
    assert got.columns == ["doc_id", "text", "lang", "lang_pred", "score"] and {r.lang_pred for r in got.collect()} == {"x"}
    assert langid.identify(docs.limit(0), docs).count() == 0


def test_filters_follow_insertions_and_deletions(spark):
    """Stored filters hold the droppable keys alone after any sequence, and are made anew where they are outgrown."""
    lines = lambda lo, hi, times: [(i * 1000 + k, "\n".join(f"line {j}" for j in range(lo, hi))) for i in range(times) for k in range(1)]
    store = linededup.LineStore(spark, 2).insert(docs_of(spark, lines(0, 40, 2)))
    first = store
    store = store.insert(docs_of(spark, lines(20, 900, 3))).delete(docs_of(spark, lines(0, 40, 1)))
    keys = np.array([(r.h1, r.h2) for r in store.droppable().collect()], np.int64)
    filters = {r["shard"]: bytes(r["filter"]) for r in store.filters.collect()}
    assert len(keys) == 880 and sum(int(np.count_nonzero(linededup.CuckooFilter.load(f).table)) + len(linededup.CuckooFilter.load(f).stash) for f in filters.values()) == 880
    held = linededup.ShardedFilter(keys, store.shards, filters)
    assert held.drops(keys).all() and len(filters) == store.shards
    other = np.random.default_rng(1).integers(-(2**63), 2**63, (2000, 2))
    assert not held.drops(other).any() and held.passes(other).mean() < 0.01
    back = store.insert(docs_of(spark, lines(0, 40, 1))).delete(docs_of(spark, lines(20, 900, 3)))
    assert sorted(map(tuple, back.droppable().collect())) == sorted(map(tuple, first.droppable().collect()))
    for limit in (1000, 0):  # exact keys for all tasks; or a join of what passes the filters
        got = store.apply(docs_of(spark, [(1, "line 5\nline 50\n LINE 60 \nown"), (2, None)]).withColumn("N_Lines", __import__("pyspark").sql.functions.lit(1)), limit)
        assert got.columns == ["doc_id", "text", "n_lines", "n_dropped"]
        assert sorted((r.doc_id, r.text, r.n_dropped) for r in got.collect()) == [(1, "line 5\nown", 2), (2, "", 0)]


def test_license_spans_are_verified(spark):
    words = licenses.TEMPLATES["bsd"].split()
    pieces = [words[i : i + 6] for i in range(0, len(words) - 5, 6)]
    backwards = " ".join(w for p in reversed(pieces) for w in p)
    rows = [(1, licenses.TEMPLATES["bsd"]), (2, backwards), (3, " ".join(words[:20]) + " filler" * 400 + " " + " ".join(words[20:])), (1, licenses.TEMPLATES["bsd"]), (4, "q " * 50_000 + licenses.TEMPLATES["isc"]), (None, None)]
    got = sorted(((r.doc_id, r.labels) for r in licenses.license_labels(docs_of(spark, rows)).collect()), key=repr)
    assert got == sorted([(1, "bsd"), (2, ""), (3, ""), (1, "bsd"), (4, "isc"), (None, "")], key=repr)
    assert licenses.license_labels(docs_of(spark, [])).count() == 0
    _, spans = licenses.scan_licenses(docs_of(spark, [(7, "one two " + licenses.TEMPLATES["isc"])]))
    assert [(r.start, r["end"]) for r in spans.collect() if r.template == "isc"] == [(2, 2 + len(licenses.words_of(licenses.TEMPLATES["isc"].encode())))]
    assert licenses.aligned([(i, i % 3) for i in range(9)], 3, 0) and all(n <= 3 for _, _, n in licenses.aligned([(i, i % 3) for i in range(9)], 3, 0))


def test_sides_beyond_the_broadcast_bound_are_shuffled(spark, monkeypatch):
    """A few rows of very long words are too large to broadcast; matches are the same either way, long words among them."""
    long = "w" * 3000
    docs = docs_of(spark, [(1, f"a b {long} c d"), (2, None), (3, ""), (1, f"a b {long} c d"), (None, f"{long} c"), (4, "c " + long)])
    bench = spark.createDataFrame([(1, f"b {long} c"), (2, f"{long} c"), (3, None)], "item_id long, text string")
    find = lambda: sorted((tuple(r)[:3] + (tuple(r["items"]),) for r in decontam.contamination(docs, bench).collect()), key=repr)
    hinted = lambda table: "Hint" in table._jdf.queryExecution().logical().toString() or "hint" in table._jdf.queryExecution().logical().toString()
    terms = decontam.written(docs.select(docs.text.alias("term")))
    whole = find()
    assert whole == sorted([(1, 5, 3, ("1", "2")), (1, 5, 3, ("1", "2")), (2, 0, 0, ()), (3, 0, 0, ()), (None, 2, 2, ("2",)), (4, 2, 0, ())], key=repr)
    monkeypatch.setattr(decontam, "BROADCAST_BYTES", 2000)
    assert not hinted(decontam.small(terms, 32, texts=("term",))) and hinted(decontam.small(terms, 32))
    assert find() == whole


def test_queries_say_what_they_do():
    assert all(f.__doc__ for f in QUERIES.values())
