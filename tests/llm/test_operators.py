"""Each operator against brute force on small tables with nulls, empty and long texts, ties, repeated rows and clashing columns."""

import hashlib
import math
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

from rambler.llm import bpe, jaccard, langid, linededup, lm, packing, sharding, tokencount, winnow
from rambler.llm.decontam import contamination, proximity_matches
from rambler.llm.licenses import TEMPLATES, license_labels

BASE = "the quick brown fox jumps over the lazy dog while seven wizards brew potions near old river banks and sing about the moon tonight again"
TEXTS = [
    (1, BASE), (2, BASE), (3, BASE.replace("seven", "eight")), (4, None), (5, ""), (6, "   \n\t "), (7, "Short TEXT"), (8, "short text"),
    (9, BASE + "\nshared line\n" + "x" * 300), (10, "Ünïcode ß Wörter\nshared line \n" + " ".join(f"w{i}" for i in range(5000))), (11, "it's  odd white <|endoftext|> 日本語 ١٢"),
    (None, "no id here\nshared line"), (12, "\tSHARED LINE\nother"), (12, "\tSHARED LINE\nother"),
]
WORD = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
LOWER = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
SCHEMA = "doc_id long, text string, TEXT string, n long"


def table(spark, rows=TEXTS, schema=SCHEMA):
    return spark.createDataFrame([(i, t, "clash", 0) for i, t in rows], schema)


def lines_out(rows):
    return sorted(map(tuple, rows), key=repr)


def words(t):
    return WORD.findall((t or "").translate(LOWER))


def library(text):
    from tokenizers import Tokenizer

    return Tokenizer.from_file(bpe.default_vocab()).encode(text or "", add_special_tokens=False).ids


def test_ids_equal_the_library():
    b = bpe.Bpe(bpe.default_vocab())
    for _, t in TEXTS:
        assert np.frombuffer(b.encode((t or "").encode()), "<u4").tolist() == library(t)


def test_packing_is_whole(spark):
    rows = packing.pack_documents(table(spark), max_tokens=64, piece_tokens=32, batch_windows=4).collect()
    by_seq, by_doc = defaultdict(list), defaultdict(list)
    for r in rows:
        by_seq[r.sequence_id].append((r.offset, r.length))
        by_doc[r.doc_id].append((r.start, bytes(r.token_ids)))
    for pieces in by_seq.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 64
    for i, t in TEXTS:
        if i != 12:
            assert np.frombuffer(b"".join(x for _, x in sorted(by_doc[i])), "<u4").tolist() == library(t) + [1]
    assert packing.pack_documents(table(spark, [])).count() == 0


def test_differencing_balances_and_the_window_count_rises():
    assert sorted(sum([8, 7, 6, 5, 4][i] for i in p) for p in packing.differencing([8, 7, 6, 5, 4], 2)) == [14, 16]
    parts = packing.pack([7, 7, 7], 10)
    assert len(parts) == 3 and sorted(i for p in parts for i in p) == [0, 1, 2]


def test_token_counts_and_prefixes(spark):
    got = {(r.doc_id, r.n_bytes): (r.n_tokens, r.over_limit) for r in tokencount.count_tokens(table(spark), limit=20).collect()}
    for i, t in TEXTS:
        n = len(library(t))
        assert got[i, len((t or "").encode())] == (n, n > 20)
    c = tokencount.PrefixCounter(bpe.default_vocab())
    word = "internationalization"
    assert c.piece(word.encode()) == [len(library(word[:i])) for i in range(len(word) + 1)]
    assert len(library(c.cut(BASE, 7))) <= 7 < len(library(c.cut(BASE, 7) + " zz zz"))


def test_line_dedup(spark):
    docs = table(spark)
    want = []
    keys = Counter(k for _, t in TEXTS for k in {x.strip(" \t\n\x0b\x0c\r").translate(LOWER) for x in (t or "").split("\n")} - {""})
    for i, t in TEXTS:
        kept = [x for x in (t or "").split("\n") if keys[x.strip(" \t\n\x0b\x0c\r").translate(LOWER)] < 3]
        want.append((i, "\n".join(kept), len((t or "").split("\n")), len((t or "").split("\n")) - len(kept)))
    for limit in (1000, 0):  # broadcast keys, and the join beyond the bound
        got = linededup.dedup_lines(docs.drop("n"), 3, limit)
        assert got.columns == ["doc_id", "text", "TEXT", "n_lines", "n_dropped"]
        assert lines_out((r[0], r[1] or "", r[3], r[4]) for r in got.collect()) == lines_out(want)
    assert linededup.dedup_lines(table(spark, []).drop("n")).count() == 0


def test_line_store_is_reversible(spark):
    a, b = table(spark, TEXTS[:9]), table(spark, TEXTS[9:])
    once = linededup.LineStore(spark, 2).insert(a)
    back = once.insert(b).delete(b)
    assert lines_out(once.state.collect()) == lines_out(back.state.collect())


def test_cuckoo_filter_deletes():
    keys = np.random.default_rng(1).integers(-(2**63), 2**63, (5000, 2))
    f = linededup.ShardedFilter(keys[:4000], 4)
    assert f.drops(keys).tolist() == [True] * 4000 + [False] * 1000
    for k in map(tuple, keys[:2000].tolist()):
        f.remove(k)
    f.add(tuple(keys[4500].tolist()))
    assert np.flatnonzero(f.drops(keys)).tolist() == [*range(2000, 4000), 4500]


def test_sharding(spark):
    rows = sharding.shard_by_bytes(table(spark), 3).collect()
    assert len(rows) == len(TEXTS) and sum(r.size for r in rows) == sum(len((t or "").encode()) + 1 for _, t in TEXTS)
    assert {(r.doc_id, r.text_crc32) for r in rows} == {(i, zlib.crc32((t or "").encode())) for i, t in TEXTS}
    for k in {r.shard for r in rows}:
        assert sorted(r.slot for r in rows if r.shard == k) == list(range(sum(r.shard == k for r in rows)))
    assert sharding.shard_by_bytes(table(spark, [])).count() == 0


def test_jaccard(spark):
    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").translate(LOWER))
        return {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set()

    extra = [(100 + i, " ".join(f"t{(i * 3 + j) % 40 if j % 9 else i * 50 + j}" for j in range(60))) for i in range(12)]
    rows = TEXTS[:11] + extra
    sets = {i: shingles(t) for i, t in rows}
    comp = {i: i for i in sets}
    for _ in sets:
        for a in sets:
            for b in sets:
                if sets[a] and sets[b] and 100 * len(sets[a] & sets[b]) >= 75 * len(sets[a] | sets[b]):
                    comp[a] = comp[b] = min(comp[a], comp[b])
    got = {r.doc_id: (r.n_shingles, r.component_id) for r in jaccard.jaccard_classes(table(spark, rows)).collect()}
    assert got == {i: (len(sets[i]), comp[i]) for i in sets}
    assert jaccard.jaccard_classes(table(spark, [])).count() == 0


def test_contamination(spark):
    items = [(1, " ".join(words(BASE)[3:16])), (2, "shared line"), (3, None), (4, ""), (5, "never stands anywhere at all in these few texts of ours today"), (None, "short text")]
    bench = spark.createDataFrame(items, "item_id long, text string")
    got = lines_out((r.doc_id, r.n_words, r.n_hit, tuple(r["items"]), r.contaminated) for r in contamination(table(spark), bench, 10).collect())
    want = []
    for i, t in TEXTS:
        w, hit, names = words(t), set(), set()
        for item, text in items:
            v = words(text)
            for s in range(max(0, len(v) - 10) + 1 if v else 0):
                win = v[s : s + 10]
                for p in range(len(w) - len(win) + 1):
                    if w[p : p + len(win)] == win:
                        hit |= set(range(p, p + len(win)))
                        names.add("null" if item is None else str(item))
        want.append((i, len(w), len(hit), tuple(sorted(names)), bool(hit)))
    assert got == lines_out(want)
    assert contamination(table(spark, []), bench).count() == 0
    near = proximity_matches(table(spark, [(1, "a b c a d b")]), spark.createDataFrame([("a", "b", 2)], "left string, right string, within int")).collect()
    assert sorted((r.pos_left, r.pos_right) for r in near) == [(0, 1), (3, 5)]


def test_licenses(spark):
    rows = [(1, "This is the MIT License. " + TEMPLATES["mit"]), (2, TEMPLATES["bsd"].replace("binary forms", "binary and other forms")), (3, BASE), (4, None), (5, "Apache-License mit license mit license")]
    got = {r.doc_id: r for r in license_labels(table(spark, rows)).collect()}
    assert got[1].labels == "mit" and got[1].n_base == 1 and (got[1].first_word, got[1].last_word) == (3, 3)
    assert got[2].labels == "bsd" and got[2].base_labels == "" and 0.6 <= got[2].score < 1
    assert got[3].labels == "" and got[3].score == 0 and got[4].n_words == 0 and got[4].first_word is None
    assert (got[5].n_base, got[5].first_word, got[5].last_word, got[5].base_labels) == (3, 0, 4, "apache,mit")


def test_winnowing_guarantee_and_edits(spark):
    rng = np.random.default_rng(3)
    common = "".join(rng.choice(list("abcdefgh"), 16 + 64 - 1))
    for _ in range(20):
        a, b = ("".join(rng.choice(list("ijkl"), rng.integers(0, 200))) + common + "".join(rng.choice(list("mnop"), 90)) for _ in range(2))
        assert set(winnow.winnow(a)[0]) & set(winnow.winnow(b)[0])
    h, at = winnow.winnow("aaaaaaaaaaaa", 4, 3)
    assert at.tolist() == [2, 3, 4, 5, 6, 7, 8]  # rightmost of equal ones
    rows = [r for r in TEXTS if r[0] is not None][:-1]
    got = {r.doc_id: r for r in winnow.edited_fingerprints(table(spark, rows), ranges=3).collect()}
    order = sorted(rows, reverse=True)
    for k, (i, t) in enumerate(order):
        t, following = t or "", order[(k + 1) % len(order)][1] or ""
        m = len(t) // 3
        assert got[i].n_chars == len(t) and got[i].edited_text == t[: len(t) - m] + following[:m]
    assert got[1].fingerprint == got[2].fingerprint and got[2].near_next == 1
    assert winnow.edited_fingerprints(table(spark, [])).count() == 0 and winnow.edited_fingerprints(table(spark, rows[:1])).count() == 1


def test_lm_base_score_and_ctw(spark):
    docs = [(i, t) for i, t in TEXTS if i is not None] + [(i, BASE[: i % 90]) for i in range(20, 60)]
    got = lm.score_documents(table(spark, docs), head_words=5).collect()
    counts = Counter()
    for i, t in docs:
        if zlib.crc32(str(i).encode()) % 10:
            counts.update((t or "").encode().lower().split() + [None])
    n, v = sum(counts.values()), len(counts)
    want = []
    for i, t in docs:
        w = (t or "").encode().lower().split() + [None]
        want.append((i, zlib.crc32(str(i).encode()) % 10 == 0, len(w), sum(counts[x] > 0 for x in w), n, round(sum(math.log10((counts[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w), 6)))
    assert lines_out((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 6)) for r in got) == lines_out(want)
    assert all(r.score < 0 for r in got)


def test_ctw_against_recursion():
    """The tables give what the recursion over contexts gives, and each context's byte probabilities sum to 1."""
    raws = [b"abracadabra", b"banana band", b""]
    keys, n = np.unique(lm.grams(raws)[0], return_counts=True)
    context, byte = keys >> 8, (keys & 255).astype(np.int64)
    rows, roots = [], []
    for last in np.unique(context & 255):
        mine = (context & 255) == last
        r, whole, counts = lm.subtree(context[mine].astype(np.int64), byte[mine], n[mine])
        rows += r
        roots.append((int(last), whole, counts))
    model = lm.ByteModel(np.array([c for c, _ in rows]), np.array([v for _, v in rows]), roots)
    assert np.allclose((10.0 ** model.logs.astype(float)).sum(1), 1, atol=1e-4)

    seen = defaultdict(Counter)
    for k, c in zip(keys.tolist(), n.tolist()):
        for d in range(4):
            seen[(k >> 8) & ((1 << 8 * d) - 1), d][k & 255] += c

    def kt(a, b):
        return math.lgamma(a + 0.5) + math.lgamma(b + 0.5) - math.lgamma(a + b + 1) - math.log(math.pi)

    def split(ctx, d, depth, prefix):
        ones = sum(c for x, c in seen[ctx, d].items() if x >> (8 - depth) == prefix and (x >> (7 - depth)) & 1)
        return sum(c for x, c in seen[ctx, d].items() if x >> (8 - depth) == prefix) - ones, ones

    def weighted(ctx, d, depth, prefix):
        own = kt(*split(ctx, d, depth, prefix))
        if d == 3:
            return own
        below = sum(weighted(c, d + 1, depth, prefix) for c, e in list(seen) if e == d + 1 and c & ((1 << 8 * d) - 1) == ctx)
        return np.logaddexp(own, below) - math.log(2)

    def conditional(path, d, depth, prefix):
        ctx = path & ((1 << 8 * d) - 1)
        a, b = split(ctx, d, depth, prefix)
        own = (b + 0.5) / (a + b + 1)
        if d == 3:
            return own
        share = math.exp(kt(a, b) - math.log(2) - weighted(ctx, d, depth, prefix))
        return share * own + (1 - share) * conditional(path, d + 1, depth, prefix)

    total = 0.0
    for k in lm.grams([b"band"])[0].tolist():
        for depth in range(8):
            p = conditional(k >> 8, 0, depth, (k & 255) >> (8 - depth))
            total += math.log10(p if (k >> (7 - depth)) & 1 else 1 - p)
    assert model.scores([b"band"])[0] == pytest.approx(total, abs=1e-3)


def test_language_id(spark):
    rng = np.random.default_rng(5)
    syllables = {"en": ["the", "ing", "and", "her"], "de": ["sch", "ung", "ein", "für"], "es": ["que", "ción", "los", "ñar"]}
    rows = [(i, " ".join("".join(rng.choice(syllables[k], 3)) for _ in range(25)), k) for i, k in enumerate(["en", "de", "es"] * 40)]
    docs = spark.createDataFrame([*rows, (900, None, "en"), (901, "123 !!", "de"), (902, "", None)], "doc_id long, text string, lang string")
    got = {r.doc_id: r for r in langid.identify(docs, docs.where("doc_id % 3 <> 1 or doc_id < 60")).collect()}
    assert all(got[i].lang_pred == k and 0 <= got[i].score <= 1 for i, _, k in rows)
    assert all(got[i].lang_pred == "und" and got[i].score == 0 for i in (900, 901, 902))
    assert langid.identify(docs, docs.limit(0)).where("lang_pred <> 'und'").count() == 0


def test_forward_sums_all_segmentations():
    pieces = {"▁": 0, "a": 1, "b": 2, "ab": 3, "▁a": 4}
    p = np.array([[0.1], [0.2], [0.3], [0.15], [0.25], [1e-6]])
    got = math.exp(langid.Lattice(["▁ab"], pieces).likelihoods(p)[0, 0])
    assert got == pytest.approx(0.1 * 0.2 * 0.3 + 0.1 * 0.15 + 0.25 * 0.3)


def test_pipeline_stages(spark, tmp_path):
    import corpus_pipeline as c

    rows = [(i, t, "en", "s", len(t or "")) for i, t in TEXTS[:9]] + [(50 + k, f"clean words number {k} stay here as they are without any copy\nrepeated footer", "en", "s", 10) for k in range(12)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, " ".join(words(TEXTS[2][1])[3:15]))], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = c.documents(spark, str(tmp_path))
    kept = []
    for name, stage in c.STAGES[:-1]:
        docs = c.written(stage(spark, docs, str(tmp_path)))
        assert tuple(docs.columns) == c.COLUMNS
        kept.append({r.doc_id: r.text for r in docs.collect()})
    assert set(kept[0]) == {i for i, t, *_ in rows if re.search(r"[^\W\d_]", t or "")}
    assert set(kept[1]) == set(kept[0]) and all("repeated footer" not in t for t in kept[1].values())
    assert set(kept[2]) == set(kept[1]) - {2, 8, 9}  # 3 shares 16 of 26 shingles with 1, and 9 holds 1 whole
    assert set(kept[3]) == set(kept[2]) - {3}
    assert {r.doc_id for r in c.run(spark, str(tmp_path)).collect()} == set(kept[3])


