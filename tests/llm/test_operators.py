"""Each operator against a brute-force form on small, odd tables."""

from __future__ import annotations

import math
import random
import re
import time
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash
import zstandard

from batchfeed.llm import decontaminate, katz, key_exchange, mixing, quality_model, quality_rules, queries, simhash, substring_dedup, token_files, url_filters, warc
from batchfeed.llm.queries import vocabulary_path

random.seed(7)
WORDS = ["alpha", "beta", "Gamma", "dü", "漢", "x1"]
LONG = " ".join(random.choice(WORDS) + str(i) for i in range(60))


def odd_documents():
    """Nulls, empties, copies, near copies, repeated rows, one long text."""
    rows = [(0, None, None), (1, "", "a"), (2, "one", "a"), (3, LONG, "b"), (4, LONG, "b"), (5, LONG + " more words", "b"), (5, LONG + " more words", "b"), (6, "  odd \t spaces\n\nlines   x ", None), (None, LONG, "c")]
    rows += [(10 + i, " ".join(random.choice(WORDS) for _ in range(random.randint(1, 80))), random.choice("abc")) for i in range(40)]
    rows.append((99, " ".join(random.choice(WORDS) for _ in range(5000)), "a"))
    return rows


DOCS = odd_documents()


@pytest.fixture(scope="module")
def docs(spark):
    return spark.createDataFrame([(*r, 1, "x") for r in DOCS], "doc_id long, text string, source string, n_words int, kept string").repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], "doc_id long, text string, source string, n_words int, kept string")


def words(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def key(x):
    return tuple("" if v is None else str(v) for v in x)


def test_substring_dedup(docs, empty):
    best = {}
    for i, t, _ in DOCS:
        w = words(t)
        for k in range(len(w) - 12):
            g = tuple(w[k : k + 13])
            best[g] = min(best.get(g, math.inf), math.inf if i is None else i)
    want = []
    for i, t, _ in DOCS:
        w = words(t)
        gone = {k + j for k in range(len(w) - 12) if best[tuple(w[k : k + 13])] < (math.inf if i is None else i) for j in range(13)}
        want.append((i, len(w), len(gone), " ".join(x for k, x in enumerate(w) if k not in gone)))
    for options in ({"longest": None}, {"fan": 3}):  # one exchange of all parts, and several levels of it
        out = substring_dedup.remove_repeats(docs, keep_text=True, block_bytes=2000, **options).collect()
        assert sorted((key((r.doc_id, r.n_words, r.n_removed, r.kept_text)) for r in out)) == sorted(map(key, want))
        assert {r.longest_repeat for r in out if r.doc_id == 4} == {52 if "longest" in options else 13}
    assert substring_dedup.remove_repeats(empty).count() == 0


def test_substring_query_doubles_until_nothing_repeats(spark, tmp_path, monkeypatch):
    assert substring_dedup._ladder(13, 60) == [1, 2, 4, 7, 13, 26, 52]
    copied = " ".join(f"w{i}" for i in range(120))
    spark.createDataFrame([(1, copied), (2, "other words " + copied), (3, " ".join(copied.split()[:30]))], "doc_id long, text string").write.parquet(str(tmp_path / "documents.parquet"))
    monkeypatch.setattr(substring_dedup, "digest", lambda found: found)
    got = queries.op4_substring_dedup(spark, str(tmp_path)).collect()
    assert {r.doc_id: (r.longest_repeat, r.n_removed) for r in got} == {1: (104, 0), 2: (104, 120), 3: (26, 30)}


def test_next_windows_are_those_whose_halves_repeat():
    numbers = [np.array([0]), np.array([0], np.uint8)]
    state = substring_dedup.State.of(key_exchange.Block(0, 0, *numbers, zstandard.ZstdCompressor().compress(np.array([9], "<u8").tobytes() + b"a b c d e")))
    ladder = substring_dedup._ladder(4, 8)
    keys, place, _ = substring_dedup._asks(state, ladder, 0, 4)
    assert ladder == [1, 2, 4, 8] and sorted(state.hashes(ladder, 1)) == keys.tolist() and len(place) == 5  # every word is asked about
    state.climb(ladder, 0, 4, np.array([True, True, True, False, True]))
    assert state.at.tolist() == [0, 1]
    state = substring_dedup.State.loaded(state.dumped())
    state.climb(ladder, 1, 4, np.array([True, True]))
    assert state.at.tolist() == [] and len(state.numbers) == 0  # two words at 0 and 2 would be needed


def test_a_block_carries_words_or_window_hashes_whichever_is_smaller():
    """Both give the same keys; a block in which all repeats keeps its words, however long the windows get."""
    ladder = substring_dedup._ladder(4, 64)
    body = [b" ".join(b"w%d" % i for i in range(100)), b" ".join([*(b"w%d" % i for i in range(40)), *(b"v%d" % i for i in range(2000))])]
    raw = np.array([len(b) for b in body], "<u8").tobytes() + b"".join(body)
    state = substring_dedup.State.of(key_exchange.Block(0, 0, np.arange(2), np.zeros(2, np.uint8), zstandard.ZstdCompressor().compress(raw)))
    words, numbers, seen = state.vocabulary, state.numbers, {}
    for level, length in enumerate(ladder):
        state = substring_dedup.State.loaded(state.dumped())
        seen[length] = len(state.at), len(state.numbers) > 0
        keys, _, values = substring_dedup._asks(state, ladder, level, 4)
        if length >= 4 and seen[length] == (len(state.at), False):
            anew = substring_dedup.State(state.sizes, state.ids, words, numbers, state.at, state.first, state.second, state.gone, state.most)
            other, _, same = substring_dedup._asks(anew, ladder, level, 4)
            assert keys.tolist() == other.tolist() and [v.tolist() for v in values] == [v.tolist() for v in same]
        answer = substring_dedup._repeated_long if length >= 4 else substring_dedup._repeated_short
        substring_dedup._judge(state, ladder, level, 4, answer(keys, np.arange(len(keys)), values)[0])
    assert seen == {1: (2140, True), 2: (78, True), 4: (74, False), 8: (66, False), 16: (50, False), 32: (18, False), 64: (0, False)}
    assert state.gone.sum() == 40 and state.most.tolist() == [32, 32]


def test_windows_that_share_a_key_are_told_apart():
    a = np.array([5, 5, 5, 7, 3], np.uint64)
    keys, place, first = substring_dedup._distinct(a, np.array([1, 2, 1, 9, 4], np.uint64))
    assert keys.tolist() == [3, 5, 5, 7] and place.tolist() == [1, 2, 1, 3, 0] and first.tolist() == [4, 0, 1, 3]
    values = [np.array([4, 4, 6, 1, 2]), np.zeros(5, np.uint8), np.array([1, 2, 1, 9, 4], np.uint64)]
    keys, place = np.unique(a, return_inverse=True)
    assert substring_dedup._repeated_long(keys, place, values)[0][0].tolist() == [1, 0, 3, 0, 0]


def test_words_are_cut_where_the_pattern_cuts():
    bodies = [b"", b" \t a  b\n", "x\u00a0y\x1c\x85z \u2003\x00 \x0b\x0c\r é".encode(), b"   ", b"a", b"\xff\xfe b", b""]
    want = [re.findall(rb"[^\x20\x09-\x0D]+", b) for b in bodies]
    flat = [w for b in want for w in b]
    body, lengths, sizes = substring_dedup.spaced_words(bodies)
    assert sizes.tolist() == [len(b) for b in want] and lengths.tolist() == [len(w) + 1 for w in flat]
    assert body.tobytes() == b"".join(w + b" " for w in flat)
    assert [x.tolist() for x in substring_dedup.spaced_words([])] == [[], [], []]


def test_equal_hashes_meet_however_close_others_are():
    rng = np.random.default_rng(4)
    close = np.uint64(1 << 63) + rng.integers(0, 90, 3000).astype(np.uint64)  # differ where the places stand
    far = rng.integers(0, 1 << 63, 400).astype(np.uint64)[rng.integers(0, 400, 3000)]
    for hashes in (close, far, np.append(close, far), close[:1], close[:0]):
        keys, first, place = np.unique(hashes, return_index=True, return_inverse=True)
        got = substring_dedup._distinct(hashes)
        assert [x.tolist() for x in got] == [keys.tolist(), place.tolist(), first.tolist()]


def test_a_block_is_asked_about_in_half_the_time_its_words_take_as_objects():
    rng = np.random.default_rng(5)
    body = b" ".join(b"word%d" % i for i in rng.zipf(1.2, 400_000) % 90_000)
    raw = np.array([len(body)], "<u8").tobytes() + body
    block = key_exchange.Block(0, 0, np.array([0]), np.zeros(1, np.uint8), zstandard.ZstdCompressor().compress(raw))

    def as_objects():
        found = body.split()
        number = {w: i for i, w in enumerate(dict.fromkeys(found))}
        numbers = np.fromiter(map(number.__getitem__, found), np.uint64, len(found))
        return np.unique(numbers, return_index=True, return_inverse=True)

    def seconds(run):
        began = time.process_time()
        run()
        return time.process_time() - began

    def in_arrays():
        return substring_dedup._asks(substring_dedup.State.of(block), substring_dedup._ladder(13, 13), 0, 13)

    assert 2 * min(seconds(in_arrays) for _ in range(5)) < min(seconds(as_objects) for _ in range(5))


def test_exchange_rows_grow_with_the_input(spark):
    """A block has at most about `fan` rows a level, however many parts there are; all entries are answered."""
    rng = np.random.default_rng(6)
    spans = {}
    for n in (16, 64):
        ex = key_exchange.Exchange(tuple(key_exchange.ladder(4 * n, 8)), n)
        keys = {b: np.unique(rng.integers(0, 1 << 63, 200).astype(np.uint64) * np.uint64(2) + np.uint64(b % 2)) for b in range(n)}
        for b in range(n):
            keys[b][:20] = np.unique(keys[0][:20])  # shared by all
            keys[b] = np.unique(keys[b])
        rows = [r for b in range(n) for r in key_exchange.ask_rows(b, b, keys[b], [np.full(len(keys[b]), b)], ex.first).to_pylist()]
        asks = spark.createDataFrame([tuple(r.values()) for r in rows], key_exchange.ASK_SCHEMA).repartition(4)
        merged, total, blocks, level = asks, asks.count(), n, []
        for parts, finer in zip(ex.levels, ex.levels[1:]):
            groups = -(-blocks // parts)
            blocks = groups * parts
            merged = key_exchange._merged(merged, parts, finer, groups).where("kind = 'ask'").drop("kind")
            level.append(merged.count())
        spans[n] = (total + sum(level)) / n / (1 + len(level))
        assert len(ex.levels) > 1 and spans[n] <= 2 * 8
        answer = lambda k, place, values: ([np.bincount(place, minlength=len(k))[place].astype(np.int64)], [])
        got = {}
        for r in key_exchange.answered(asks, ex, answer).collect():
            got.setdefault(r.block, []).append(r.asDict())
        often = Counter(k for b in keys for k in keys[b].tolist())
        for b in range(n):
            assert key_exchange.values_in_order(got[b], b)[0].tolist() == [often[k] for k in keys[b].tolist()]


def test_simhash(docs, empty):
    def fp(t):
        w = words((t or "").translate({c: c + 32 for c in range(65, 91)}))
        s = [" ".join(w[i : i + 3]) for i in range(max(1, len(w) - 2))] if w else []
        h = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    f = [fp(t) for _, t, _ in DOCS]
    group = list(range(len(f)))
    for _ in f:
        group = [min(group[j] for j in range(len(f)) if (f[i] ^ f[j]).bit_count() <= 2) for i in range(len(f))]
    low = {g: min((DOCS[j][0] for j in range(len(f)) if group[j] == g and DOCS[j][0] is not None), default=None) for g in group}
    want = sorted(key((i, f"{x:016x}", low[g])) for (i, _, _), x, g in zip(DOCS, f, group))
    for most in (24, 1):
        assert sorted(key(r) for r in simhash.near_duplicates(docs, max_bucket=most).collect()) == want
    best = {}
    for j, g in enumerate(group):
        best[g] = min([best.get(g), DOCS[j][0]], key=lambda i: (i is None, i or 0)) if g in best else DOCS[j][0]
    for most in (1_000_000, 0):  # broadcast or not
        kept = simhash.keep_first(docs.withColumnRenamed("kept", "text_hash"), broadcast_rows=most)
        assert kept.schema == docs.withColumnRenamed("kept", "text_hash").schema and Counter(r.doc_id for r in kept.collect()) == Counter(best.values())
    assert simhash.near_duplicates(empty).count() == 0 and simhash.keep_first(empty).count() == 0


def test_simhash_keeps_rows_of_one_id_apart(spark):
    """A repeated or null doc_id with other texts is not taken for a copy; equal rows are."""
    a, b, c = LONG, " ".join(reversed(LONG.split())), "other words that stand alone"
    rows = [(5, a), (5, b), (3, b), (None, c), (None, "and yet another text here"), (7, a), (8, "t w o"), (8, "t w o")]
    kept = simhash.keep_first(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert Counter(map(tuple, kept)) == Counter([(5, a), (3, b), (None, c), (None, "and yet another text here"), (8, "t w o")])


def test_simhash_components_of_a_long_chain(spark):
    rng = random.Random(9)
    ids = [rng.getrandbits(64) - (1 << 63) for _ in range(1010)]
    low = dict(zip(ids, rng.sample(range(5000), 1010)))
    low[ids[3]] = low[ids[1003]] = None
    chain, ring = ids[:1000], ids[1000:1009]
    edges = [*zip(chain, chain[1:]), *zip(ring, ring[1:]), (ring[-1], ring[0])]
    out = simhash.components(spark.createDataFrame(list(low.items()), "fp long, low long"), spark.createDataFrame([tuple(sorted(e)) for e in edges], "a long, b long"))
    want = {f: min(low[x] for x in part if low[x] is not None) for part in (chain, ring) for f in part}
    assert {r.fp: r.label for r in out.collect()} == want and all(low[r.root] == r.label for r in out.collect())


def test_decontaminate(spark, docs, empty):
    items = [("a", " ".join(words(LONG)[5:30])), ("b", "one"), ("c", ""), ("d", None), ("e", "nothing here at all")]
    bench = spark.createDataFrame(items, "item_id string, text string")
    plain = lambda t: re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").translate({c: c + 32 for c in range(65, 91)}))
    want = []
    for i, t, _ in DOCS:
        w, hit, ids = plain(t), set(), set()
        for item, text in items:
            p = plain(text)
            n = min(13, len(p))
            for k in range(len(p) - n + 1) if n else ():
                for j in range(len(w) - n + 1):
                    if w[j : j + n] == p[k : k + n]:
                        hit |= set(range(j, j + n))
                        ids.add(item)
        want.append(key((i, len(w), len(hit), ",".join(sorted(ids)), bool(hit) and 20 * len(hit) >= len(w))))
    for most in (1 << 20, 90):
        out = decontaminate.search(docs, bench, max_pattern_bytes=most).collect()
        assert sorted(key((r.doc_id, r.n_words, r.n_hit, ",".join(r.item_ids), r.contaminated)) for r in out) == sorted(want)
    assert decontaminate.search(empty, bench).count() == 0 and decontaminate.search(docs, bench.limit(0)).where("contaminated").count() == 0
    mine = docs.withColumnRenamed("kept", "found").withColumn("_low", docs.n_words)
    clean = Counter(w[0] for w in want if w[4] == "False")
    for most in (1 << 20, 90):
        kept = decontaminate.keep_clean(mine, bench, max_pattern_bytes=most)
        assert kept.schema == mine.schema and Counter(key([r.doc_id])[0] for r in kept.collect()) == clean and {(r.n_words, r.found) for r in kept.collect()} == {(1, "x")}


def test_decontaminate_counts_items_without_id(spark):
    docs = spark.createDataFrame([(1, "one two three"), (2, "four five six")], "doc_id long, text string")
    bench = spark.createDataFrame([(None, "one two"), ("a", "two three"), (None, "five")], "item_id string, text string")
    for most in (1 << 20, 1):
        out = {r.doc_id: (r.n_hit, r.item_ids, r.contaminated) for r in decontaminate.search(docs, bench, max_pattern_bytes=most).collect()}
        assert out == {1: (3, ["a"], True), 2: (1, [], True)}


def test_quality_rules(docs, empty):
    out = {(r.doc_id, r.n_words): r for r in quality_rules.judge(docs, quality_rules.LineCRF()).collect()}
    for i, t, _ in DOCS:
        w, t = words(t), t or ""
        r = out[i, len(w)]
        tri = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        n = Counter(tri)
        lines = [x for x in t.split("\n") if words(x)]
        assert r.n_repeat_words == len({k + j for k, g in enumerate(tri) if n[g] > 1 for j in range(3)})
        assert (r.word_chars, r.n_symbols, r.n_dup_lines) == (sum(map(len, w)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)))
        assert r.base_failed == (len(w) < 50 or 100 * r.n_repeat_words > 50 * len(w)) and not (r.base_failed and r.kept)
    assert quality_rules.judge(empty, quality_rules.LineCRF()).count() == 0


def plain_lines(text):
    """Features of the lines with a word, from their definitions."""
    rows, counts, seen = [], [], []
    for line in (text or "").split("\n"):
        w = words(line)
        if not w:
            continue
        size = len(line.encode())
        share = lambda some, line=line, size=size: sum(c in some for c in line) / size
        rows.append([1, math.log1p(len(w)), min(size / len(w), 40) / 10, share("#*$%&|<>"), share("ABCDEFGHIJKLMNOPQRSTUVWXYZ"), share("0123456789"), line in seen, len(set(w)) / len(w), w[-1][-1] in ".!?", line.count("!") / size])
        counts.append(len(w))
        seen.append(line)
    return np.array(rows, float).reshape(-1, 10), counts


def test_quality_rules_keep_by_the_best_labelling(spark, docs):
    """kept against all labellings of a text's lines, with the caller's columns as they were."""
    rng = random.Random(11)
    line = lambda: rng.choice(["Plain words make a sentence here.", "## | * $ % & # |", "MENU Home LOGIN 12 34!", "some more of the usual text"])
    rows = [(i, "\n".join(line() + f" w{rng.randint(0, 10**6)} x{rng.randint(0, 10**6)} y{rng.randint(0, 10**6)}" for _ in range(rng.randint(4, 9)))) for i in range(60)]
    crf = quality_rules.LineCRF()
    want = set()
    for i, t in rows:
        x, counts = plain_lines(t)
        u = x @ crf.weights
        value = lambda p: crf.start[p[0]] + sum(a * b for a, b in zip(u, p)) + sum(crf.step[a, b] for a, b in zip(p, p[1:]))
        best = max(([k >> b & 1 for b in range(len(u))] for k in range(1 << len(u))), key=value)
        w = words(t)
        tri = [tuple(w[k : k + 3]) for k in range(len(w) - 2)]
        often = Counter(tri)
        repeats = len({k + j for k, g in enumerate(tri) if often[g] > 1 for j in range(3)})
        if len(w) >= 25 and 2 * repeats <= len(w) and sum(n for n, s in zip(counts, best) if not s) >= 0.5 * sum(counts):
            want.add(i)
    df = spark.createDataFrame([(*r, 7, "own", "z") for r in rows], "doc_id long, text string, n_words int, kept string, found string")
    kept = quality_rules.keep_good(df, crf, min_words=25)
    assert kept.schema == df.schema and {r.doc_id for r in kept.collect()} == want and 0 < len(want) < len(rows)
    assert {(r.n_words, r.kept, r.found) for r in kept.collect()} == {(7, "own", "z")}


def test_line_features_from_their_definitions():
    for t in ["", "  \n\n", "One two.\nOne two.\n\tTHREE #4!\n", "ü ü\n漢 | x " + "y" * 500, LONG]:
        x, counts, dups = quality_rules.line_features(t.encode())
        y, other = plain_lines(t)
        assert counts == other and np.allclose(x, y) and dups == y[:, 6].sum()


def test_crf_fit_is_the_maximum_of_the_likelihood():
    """Gradient of the regularised likelihood, by enumerating every labelling, vanishes at the fit."""
    rng = np.random.default_rng(5)
    sequences = []
    for _ in range(30):
        x = np.column_stack([np.ones(5), rng.normal(size=(5, 9))])
        sequences.append((x, (x[:, 1] + rng.normal(size=5) > 0).astype("u1")))
    crf = quality_rules.fit(sequences, rounds=600, rate=0.05)
    theta = np.concatenate([crf.weights, crf.step.ravel(), crf.start])

    def loss(t):
        w, step, start = t[:10], t[10:14].reshape(2, 2), t[14:]
        total = 0.0
        for x, y in sequences:
            u = x @ w
            value = lambda p: start[p[0]] + sum(a * b for a, b in zip(u, p)) + sum(step[a, b] for a, b in zip(p, p[1:]))
            total += value(y) - np.logaddexp.reduce([value([k >> b & 1 for b in range(5)]) for k in range(32)])
        return total / 150 - 1e-3 / 2 * (t @ t)

    grad = [(loss(theta + h) - loss(theta - h)) / 2e-4 for h in np.eye(16) * 1e-4]
    assert np.abs(grad).max() < 2e-3


def test_quality_rules_train(spark, docs, empty):
    """Repeated ids, conflicting labels and a very long document are all in the bounded sample."""
    labels = spark.createDataFrame([(99, 0), (99, 1), (3, 1), (5, 1), (None, 1), (4, None), (7777, 0)], "doc_id long, quality int")
    long = docs.unionByName(spark.createDataFrame([(3, "\n".join(f"line {i} of a text" for i in range(6000)), "a", 1, "x")], docs.schema))
    a, b = quality_rules.train(long, labels), quality_rules.train(long.repartition(5), labels)
    assert np.allclose(a.weights, b.weights) and not np.allclose(a.weights, quality_rules.LineCRF().weights)
    assert not np.allclose(a.weights, quality_rules.train(docs, labels).weights)  # the long document teaches
    for some, known in ((empty, labels), (docs, labels.limit(0))):
        assert np.allclose(quality_rules.train(some, known).weights, quality_rules.LineCRF().weights)


def test_viterbi_is_the_best_path():
    rng = np.random.default_rng(3)
    crf = quality_rules.LineCRF(rng.normal(size=10), rng.normal(size=(2, 2)), rng.normal(size=2))
    x = rng.normal(size=(7, 10))
    u = x @ crf.weights
    value = lambda p: crf.start[p[0]] + sum(u[i] * s for i, s in enumerate(p)) + sum(crf.step[a, b] for a, b in zip(p, p[1:]))
    paths = [[k >> i & 1 for i in range(7)] for k in range(128)]
    assert math.isclose(value(crf.decode(x)), max(map(value, paths)))


def test_token_files(docs, empty):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(vocabulary_path())
    out = token_files.round_trip(docs, vocabulary_path(), file_tokens=500).collect()
    want = Counter()
    for i, text, _ in DOCS:
        ids = np.array([*t.encode(text or "", add_special_tokens=False).ids, 0], "<u4")
        want[key((i, len(ids), zlib.crc32(ids.tobytes())))] += 1
    assert Counter(key((r.doc_id, r.n_tokens, r.ids_crc32)) for r in out) == want
    out.sort(key=lambda r: r.start)
    assert [r.start for r in out] == np.cumsum([0, *(r.n_tokens for r in out)])[:-1].tolist()
    known = [r.doc_id for r in out if r.doc_id is not None]
    assert known == sorted(known)
    assert token_files.round_trip(empty, vocabulary_path()).count() == 0


def test_coder_blocks_and_damage():
    ids = np.random.default_rng(5).zipf(1.3, 100_000).clip(max=50_000).astype("<u2")
    data = token_files.encode_file(ids, [1], [len(ids)])
    assert (token_files.decode_file(data)[0] == ids).all() and len(data) < 2 * len(ids)
    assert (token_files.decode_file(data, [2])[0] == ids[2 * token_files.BLOCK_TOKENS : 3 * token_files.BLOCK_TOKENS]).all()
    with pytest.raises(ValueError):
        token_files.decode_file(data[: len(data) // 2] + bytes(64) + data[len(data) // 2 + 64 :])


def test_katz_sums_to_one_and_scores(docs, empty):
    out = {(r.doc_id, r.n_tokens): r for r in katz.score(docs, block_bytes=3000, least_count=2).collect()}
    train = Counter()
    for i, t, _ in DOCS:
        if zlib.crc32(b"" if i is None else str(i).encode()) % 10:
            train.update([*words((t or "").translate({c: c + 32 for c in range(65, 91)})), None])
    n, v = sum(train.values()), len(train)
    for i, t, _ in DOCS:
        w = [*words((t or "").translate({c: c + 32 for c in range(65, 91)})), None]
        r = out[i, len(w)]
        assert r.train_tokens == n and r.n_known == sum(train[x] > 0 for x in w)
        assert math.isclose(r.base_score, sum(math.log10((train[x] + 0.1) / (n + 0.1 * (v + 1))) for x in w), rel_tol=1e-9)
        assert -1e9 < r.score < 0
    assert katz.score(empty).count() == 0


def test_katz_against_brute_force(spark):
    """A plain bigram model with the same discounts: equal scores, and contexts that sum to one."""
    rng = random.Random(2)
    vocab = ["a", "b", "c", "d", "e", "f", "g"]
    texts = {i: " ".join(rng.choice(vocab[: rng.randint(2, 7)] if rng.random() < 0.9 else [f"r{i % 50}"]) for _ in range(12)) for i in range(300)}
    held = lambda i: zlib.crc32(str(i).encode()) % 10 == 0
    one, two = Counter(), Counter()
    for i, t in texts.items():
        if not held(i):
            w = ["<", *t.split(), ">"]
            one.update(w)
            two.update(zip(w, w[1:]))
    n = sum(c for w, c in one.items() if w != "<")

    def kept(table, c, k=5):
        if c > k:
            return c - 0.05
        r = Counter(table)
        d = max(c - 0.5, 0.05) / c
        cap = (k + 1) * r[k + 1] / r[1] if r[1] else 1
        if r[c] and r[c + 1] and cap < 1:
            good = ((c + 1) * r[c + 1] / r[c] / c - cap) / (1 - cap)
            d = good if 0.01 < good < 0.999 else d
        return c * d

    c1, c2 = [c for w, c in one.items() if w != "<"], list(two.values())
    p1 = {w: kept(c1, c) / n for w, c in one.items() if w != "<"}
    unknown = 1 - sum(p1.values())
    seen = {h: {w: kept(c2, c) / one[h] for (g, w), c in two.items() if g == h and c >= 2} for h in one}
    alpha = {h: (1 - sum(s.values())) / (1 - sum(p1[w] for w in s)) for h, s in seen.items()}
    p = lambda h, w: seen.get(h, {}).get(w) or alpha.get(h, 1.0) * p1.get(w, unknown)
    for h in ("a", "<"):
        assert math.isclose(sum(p(h, w) for w in [*p1, "never"]), 1, rel_tol=1e-9)
    out = katz.score(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), block_bytes=700).collect()
    for r in out:
        w = ["<", *texts[r.doc_id].split(), ">"]
        assert math.isclose(r.score, sum(math.log10(p(a, b)) for a, b in zip(w, w[1:])), rel_tol=1e-9)
    table = {r.ngram: r.n for r in katz.ngram_table(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), block_bytes=700).where("order = 2").collect()}
    name = {"<": "<s>", ">": "</s>"}
    assert table == {f"{name.get(a, a)} {name.get(b, b)}": c for (a, b), c in two.items() if c >= 2}


def katz_by_hand(texts, order):
    """Scores of texts by a plain model of all n-grams up to order, singletons too."""
    grams = [Counter() for _ in range(order)]
    for i, t in texts.items():
        if zlib.crc32(str(i).encode()) % 10:
            w = ["<"] * (order - 1) + [*t.split(), ">"]
            for m in range(order):
                grams[m].update(tuple(w[k - m : k + 1]) for k in range(order - 1, len(w)))
    size = sum(grams[0].values())

    def kept(m, c, k=5):
        if c > k:
            return c - 0.05
        r = Counter(grams[m].values())
        d = max(c - 0.5, 0.05) / c
        cap = (k + 1) * r[k + 1] / r[1] if r[1] else 1
        if r[c] and r[c + 1] and cap < 1:
            good = ((c + 1) * r[c + 1] / r[c] / c - cap) / (1 - cap)
            d = good if 0.01 < good < 0.999 else d
        return c * d

    share = [{c: kept(m, c) for c in set(grams[m].values())} for m in range(order)]
    followers = {}
    for m in range(1, order):
        for g in grams[m]:
            followers.setdefault(g[:-1], []).append(g[-1])
    unknown = 1 - sum(share[0][c] for c in grams[0].values()) / size

    def p(h, w):
        if not h:
            return share[0][grams[0][w,]] / size if grams[0][w,] else unknown
        whole = sum(grams[len(h)][*h, x] for x in followers.get(h, ()))
        mine = lambda x: share[len(h)][grams[len(h)][*h, x]] / whole
        if grams[len(h)][*h, w]:
            return mine(w)
        if not whole:
            return p(h[1:], w)
        return (1 - sum(map(mine, followers[h]))) / (1 - sum(p(h[1:], x) for x in followers[h])) * p(h[1:], w)

    for h in [(), *followers]:
        assert math.isclose(sum(p(h, w) for (w,) in grams[0]) + p(h, "never"), 1, rel_tol=1e-9)
    out = {}
    for i, t in texts.items():
        w = ["<"] * (order - 1) + [*t.split(), ">"]
        out[i] = sum(math.log10(p(tuple(w[k - order + 1 : k]), w[k])) for k in range(order - 1, len(w)))
    return out


@pytest.mark.parametrize("order", [2, 3])
def test_katz_keeps_singletons(spark, order):
    rng = random.Random(4)
    texts = {i: " ".join(rng.choice("abcdefg") if rng.random() < 0.9 else f"r{i % 20}" for _ in range(9)) for i in range(120)}
    want = katz_by_hand(texts, order)
    for fan in (4096, 5):  # one exchange of all parts, and several levels of it
        out = katz.score(spark.createDataFrame(list(texts.items()), "doc_id long, text string"), order=order, least_count=1, block_bytes=700, fan=fan).collect()
        assert len(out) == len(texts) and all(math.isclose(r.score, want[r.doc_id], rel_tol=1e-9) for r in out)


def test_op1_scores_by_all_ngrams(spark, tmp_path):
    rng = random.Random(6)
    texts = {i: " ".join(rng.choice("abcdefg") if rng.random() < 0.9 else f"r{i % 20}" for _ in range(9)) for i in range(60)}
    spark.createDataFrame(list(texts.items()), "doc_id long, text string").write.parquet(f"{tmp_path}/documents.parquet")
    want = katz_by_hand(texts, 2)
    assert all(math.isclose(r.score, want[r.doc_id], rel_tol=1e-9) for r in queries.op1_katz_score(spark, str(tmp_path)).collect())


def test_statistics_and_traversal_from_their_definitions():
    for t in ["", " ", "One two two.\n\nOne two!\n", "ü # | a@b/c_d " * 9, LONG]:
        got = dict(zip(quality_model.FEATURES, quality_model.statistics(t.encode()), strict=True))
        w, b = t.encode().split(), t.encode()
        lines = [x for x in b.split(b"\n") if x.strip()]
        k, n = max(len(w), 1), max(len(b), 1)
        c = Counter(w)
        want = {"log_words": math.log1p(len(w)), "word_bytes": sum(map(len, w)) / k, "distinct_share": len(c) / k, "adjacent_repeats": sum(x == y for x, y in zip(w, w[1:])) / k, "top_word": max(c.values(), default=0) / k, "pair_repeats": 1 - len(set(zip(w, w[1:]))) / max(len(w) - 1, 1), "duplicate_lines": 1 - len(set(lines)) / max(len(lines), 1), "short_lines": sum(len(x) < 40 for x in lines) / max(len(lines), 1), "capitals": sum(65 <= x <= 90 for x in b) / n, "digits": sum(48 <= x <= 57 for x in b) / n, "pipes": b.count(b"|") / n, "at_signs": b.count(b"@") / k}
        assert all(math.isclose(got[f], v, abs_tol=1e-12) for f, v in want.items())
    rng = np.random.default_rng(4)
    x = rng.normal(size=(600, len(quality_model.FEATURES))).astype(np.float32)
    model = quality_model.fit(x, (x[:, 2] * x[:, 3] > 0).astype(float), trees=12)

    def walk(row):
        total = model.prior
        for at in model.roots:
            while model.feature[at] >= 0:
                at = model.left[at] + (row[model.feature[at]] > model.threshold[at])
            total += model.value[at]
        return 1 / (1 + math.exp(-total))

    assert np.allclose(model.scores(x), [walk(r) for r in x])


def test_quality_model_on_held_out_labels(spark):
    """op3 on sf0.01: labels of the held-out rows are told well, and reruns agree."""
    sf = "/root/testdata/sf0.01"
    out = queries.op3_quality_model(spark, sf).toPandas()
    known = out[out.held_out].merge(spark.read.parquet(f"{sf}/labels.parquet").toPandas(), on="doc_id")
    assert ((known.score >= 0.5) == (known.quality == 1)).mean() > 0.95
    assert out.sort_values("doc_id").reset_index(drop=True).equals(queries.op3_quality_model(spark, sf).toPandas().sort_values("doc_id").reset_index(drop=True))


def test_quality_model(spark, docs, empty):
    labels = spark.createDataFrame([(i, int(len(t or "") > 100)) for i, t, _ in DOCS if i is not None], "doc_id long, quality int")
    out = quality_model.classify(docs, labels, least_rows=2).collect()
    assert len(out) == len(DOCS) and all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.5) for r in out)
    assert quality_model.classify(docs, labels.limit(0)).count() == len(DOCS) and quality_model.classify(empty, labels).count() == 0
    rng = np.random.default_rng(1)
    x = rng.normal(size=(2000, len(quality_model.FEATURES))).astype(np.float32)
    y = ((x[:, 0] > 0) ^ (x[:, 1] > 0.3)).astype(float)
    model = quality_model.fit(x[:1500], y[:1500])
    assert ((model.scores(x[1500:]) > 0.5) == y[1500:]).mean() > 0.95


def test_mixing(spark, docs, empty):
    rows = [(i, " ".join(["w"] * random.randint(0, 40)), random.choice("abcd")) for i in range(3000)] + [(9000, "x y", None), (9000, "x y", None)]
    df = spark.createDataFrame([(*r, i, "x") for i, r in enumerate(rows)], "doc_id long, text string, source string, copies int, i string")
    for bucket in (300, 4000):  # several levels, and one
        options = {"bucket_docs": bucket, "reserve": 20 if bucket == 300 else 128}
        out = mixing.mix(df, **options).collect()
        assert len(out) == len(rows)
        size, target, taken, documents = Counter(), {}, Counter(), Counter()
        for r in out:
            size[r.source] += r.size
            target[r.source] = r.target
            taken[r.source] += r.size * r.copies
            documents[r.source] += r.copies
            assert 0 <= r.copies <= 3
        assert math.isclose(sum(target.values()), sum(size.values()), rel_tol=1e-9)
        for s in "abcd":
            assert target[s] <= 3 * size[s] + 1e-6 and abs(taken[s] - target[s]) <= 1
            n = sum(r[2] == s for r in rows)
            assert abs(documents[s] - n * target[s] / size[s]) < 0.02 * n + 3
        assert sorted(map(key, out)) == sorted(map(key, mixing.mix(df, **options).collect()))
        kept = mixing.mix(df, keep_columns=True, **options)
        assert kept.schema == df.schema and Counter(r.doc_id for r in kept.collect()) == +Counter(x for r in out for x in [r.doc_id] * r.copies)
    assert mixing.mix(docs).count() == len(DOCS) and mixing.mix(empty).count() == 0 and mixing.mix(empty, keep_columns=True).count() == 0


@pytest.mark.parametrize("folder", ["sf0.001", "sf0.01"])
def test_mixing_meets_every_target_of_the_tables(spark, folder):
    """Off by less than half of the source's few smallest documents together, if it has any fraction to decide."""
    df = queries.op5_cube_mixing(spark, f"/root/testdata/{folder}").toPandas()
    source = spark.read.parquet(f"/root/testdata/{folder}/documents.parquet").select("doc_id", "source").toPandas()
    for _, g in df.merge(source, on="doc_id").groupby("source", dropna=False):
        small = g["size"][g["size"] > 0].nsmallest(3).sum()
        assert (g.taken <= 3 * g["size"]).all() and abs(g.taken.sum() - g.target.iloc[0]) <= max(small, 1)


def test_flight_keeps_the_totals():
    rng = np.random.default_rng(2)
    size = rng.integers(1, 500, 400).astype(float)
    p, noise = np.full(400, 0.3), rng.random(400)
    measures = np.stack([np.ones(400), size], axis=1)
    flown = mixing.fly(p, measures, noise)
    assert ((flown > 0) & (flown < 1)).sum() <= 2 and math.isclose(flown @ size, p @ size) and math.isclose(flown.sum(), p.sum())
    few = mixing.decide_large(p, measures, noise)
    left = (few > 0) & (few < 1)
    assert left.sum() <= 12 and math.isclose(few @ size, p @ size)
    assert abs(mixing.settle(mixing.land(few, size, p @ size), size, p @ size) @ size - p @ size) <= size.min() / 2 + 1e-6


def test_warc(spark):
    pages = [(1, "http://a/", "x"), (2, "http://b/", "x"), (3, None, None), (None, "http://c/\n", "y"), (4, "http://d/", "x"), (5, "http://e/", "ü" * 50)]
    df = spark.createDataFrame([(*p, 1) for p in pages], "page_id long, url string, html string, refers_to int")
    for most in (500_000, 0):  # the list of repeated payloads broadcast or not
        out = warc.round_trip(df, broadcast_rows=most).collect()
        got = {r.page_id: r for r in out}
        assert {i: r.refers_to for i, r in got.items()} == {1: 4, 2: 4, 3: None, None: None, 4: None, 5: None}
    twice = warc.round_trip(df.union(df)).collect()
    assert Counter((r.page_id, r.record_type, r.refers_to) for r in twice) == Counter((i, r.record_type, r.refers_to) for i, r in got.items() for _ in (0, 1))
    long = spark.createDataFrame([(1, "http://l/" + "p" * 5000, "z" * 3_000_000)], "page_id long, url string, html string")
    assert warc.round_trip(long).first().payload_bytes == 3_000_000
    assert len(out) == len(pages) and got[4].record_type == "response" and got[1].refers_to == 4 and got[2].record_type == "revisit"
    for i, _, html in pages:
        body = (html or "").encode()
        assert got[i].payload_bytes == len(body) and got[i].payload_digest == warc.payload_digest(body) and len(got[i].requests) == len(got[i].metadata) == 1
    assert bytes(got[5].capture.body) == ("ü" * 50).encode()
    assert warc.round_trip(df.limit(0)).count() == 0


def test_warc_digest_sees_the_links(spark):
    schema = "type string, record_id string, concurrent_to array<string>, url string, page_id long, refers_to long, payload_bytes long, payload_digest string, body binary"
    row = lambda kind, name, hubs, url, page=None: (kind, name, hubs, url, page, None, None, None, None)
    right = [row("response", "a", [], "u", 1), row("request", "b", ["a"], "u"), row("metadata", "c", ["a"], "u"), row("revisit", "d", ["e", "f"], None, 2), row("request", "e", [], None), row("metadata", "f", [], None)]
    result = lambda rows: warc.digest(warc.assemble(spark.createDataFrame(rows, schema)))
    assert sorted((r.page_id, r.record_type) for r in result(right).collect()) == [(1, "response"), (2, "revisit")]
    assert "Join" in result(right)._jdf.queryExecution().optimizedPlan().toString()
    lost, doubled = right[:2] + right[3:], [*right, row("request", "g", ["a"], "u")]
    swapped = [row("request", "b", ["d"], "u") if r[1] == "b" else row("revisit", "d", ["f"], None, 2) if r[1] == "d" else row("request", "e", ["a"], None) if r[1] == "e" else r for r in right]
    for wrong in (lost, doubled, swapped):
        with pytest.raises(Exception, match="one request and one metadata"):
            result(wrong).collect()


def test_url_filters(spark):
    urls = [None, "", "no scheme", "http://www.Example.com/en/x?q", "https://example.com/en/", "http://example.com", "http://a.net/fr/1#t", "ftp://net/es/", "http://com/", "http://xcom/", "http://a.b.example.com/de/"]
    df = spark.createDataFrame([(i, u, "x", 1) for i, u in enumerate(urls)], "page_id long, url string, verdict string, keys int")
    want = [(None, "allow"), (None, "allow"), (None, "allow"), ("www.example.com/en/", "allow"), ("example.com/en/", "block"), (None, "allow"), ("net/fr/", "block"), ("net/es/", "block"), ("com/", "allow"), (None, "allow"), ("com/", "allow")]
    for options in ({}, {"shards": 2}, {"local_keys": 0}):
        assert [(r.rule, r.verdict) for r in url_filters.judge(df, **options).orderBy("page_id").collect()] == want
    assert [r.verdict for r in url_filters.judge(df.union(df)).orderBy("page_id").collect()] == [v for _, v in want for _ in (0, 1)]
    assert url_filters.judge(df.limit(0)).count() == 0 and {r.verdict for r in url_filters.judge(df, rules=()).collect()} == {"allow"}
    long = spark.createDataFrame([(1, "http://" + "a." * 300 + "net/es/" + "x" * 200_000), (None, "http://" + "b" * 100_000 + ".com/")], "page_id long, url string")
    assert sorted((r.verdict, r.rule) for r in url_filters.judge(long).collect()) == [("allow", "com/"), ("block", "net/es/")]


def test_url_filters_with_many_rules(spark):
    """Against a plain look at every rule; sets too large for one small filter are cut into shards."""
    rng = random.Random(8)
    rules = tuple((rng.choice(["allow", "block"]), f"h{i % 90}.net" if i % 2 else f"x.h{i % 70}.net", rng.choice(["/", "/a/", "/a/b"])) for i in range(400))
    urls = [f"http://{rng.choice(['', 'x.', 'y.x.'])}h{rng.randrange(120)}.net{rng.choice(['', '/', '/a/', '/a/b/c', '/q'])}" for _ in range(600)]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")

    def plain(url):
        host, _, path = url[7:].partition("/")
        path = "/" + path if "/" in url[7:] else ""
        fit = [(len(h + p), len(h), h + p, v) for v, h, p in rules if ("." + host).endswith("." + h) and path.startswith(p)]
        return max(fit)[2:] if fit else (None, "allow")

    for options in ({}, {"local_keys": 0, "max_filter_bytes": 100}):
        assert [(r.rule, r.verdict) for r in url_filters.judge(df, rules, **options).orderBy("page_id").collect()] == [plain(u) for u in urls]


@pytest.mark.parametrize("local_keys", [0, 300, 100_000])
def test_cascade_is_exact(spark, local_keys):
    keys = spark.range(5000).selectExpr("xxhash64(id) h1", "xxhash64(id, 'second') h2", "id")
    listed = keys.where("id % 7 = 0")
    c = url_filters.build_cascade(listed.union(listed), keys.union(keys), first_rate=0.3, local_keys=local_keys)
    p = keys.toPandas()
    assert len(c.levels) > 1 and (c.listed(p.h1.to_numpy(), p.h2.to_numpy()) == (p.id % 7 == 0)).all()
    assert not url_filters.build_cascade(keys.limit(0), keys).levels


def test_cached_tokenizer_gives_the_ids_of_the_library():
    t, r = token_files.CachedTokenizer(vocabulary_path()), random.Random(5)
    pieces = ["a", "Zo", "é", "the", "'s", " ", " ", "\n", "\n", "\t", "\r", "\xa0", "\x1c", ".", "!)", "12", "<|endoftext|>", "中", "🙂", "²"]
    texts = ["".join(r.choices(pieces, k=r.randint(0, 14))) for _ in range(4000)] + ["".join(r.choices("ab \n.", k=r.randint(0, 9))) for _ in range(4000)]
    texts += [None, "\n", "\n\n", " \n", "a\n\n", "\n\na", "a\n\nb\n\n\nc", "x " * 400_000]
    want = t.model.encode_batch_fast([x or "" for x in texts], add_special_tokens=False)
    for _ in range(2):  # learned, then known
        assert [np.frombuffer(g, t.kind).tolist() for g in t.encode(texts)] == [e.ids for e in want]
    assert t.encode([]) == []
    small = token_files.CachedTokenizer(vocabulary_path(), limit=200)  # units move between generations and are dropped
    for at in range(0, len(texts), 500):
        assert [np.frombuffer(g, t.kind).tolist() for g in small.encode(texts[at : at + 500])] == [e.ids for e in want[at : at + 500]]
    assert small.older
