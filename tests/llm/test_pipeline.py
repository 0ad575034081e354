"""The corpus pipeline, stage by stage, against plain forms of its operators."""

from __future__ import annotations

import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
import xxhash

import corpus_pipeline
from batchfeed.llm import mixing, quality_rules
from batchfeed.llm.common import written
from batchfeed.llm.queries import vocabulary_path

rng = random.Random(17)
VOCABULARY = ["".join(rng.choice("abcdefghijklmnopqrstuvwxyz") for _ in range(rng.randint(2, 9))) for _ in range(4000)]


def sentence_text(n):
    return " ".join(rng.choice(VOCABULARY) for _ in range(n)) + "."


def split(t):
    return re.findall(r"[^\x20\x09-\x0D]+", t or "")


def plain(t):
    return re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", (t or "").lower())


def print_of(t):
    w = split(t.lower())
    h = [xxhash.xxh64_intdigest(" ".join(w[i : i + 3]).encode(), 42) for i in range(max(1, len(w) - 2))]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))


BENCH = [(k, sentence_text(30)) for k in range(4)]
CLEAN = [sentence_text(rng.randint(60, 200)) for _ in range(60)]
ROWS = [(10 + i, t, rng.choice(["a", "b", None])) for i, t in enumerate(CLEAN)]
ROWS += [(200 + i, CLEAN[3], "a") for i in range(5)] + [(5, CLEAN[7], "b"), (11, CLEAN[1], "a"), (11, CLEAN[1], "a")]
ROWS += [(300 + i, BENCH[i][1] + " " + sentence_text(80), "b") for i in range(4)]
ROWS += [(400, None, "a"), (401, "", "a"), (402, "too short", "a"), (403, "one two three " * 60, "b"), (None, sentence_text(90), None)]
ROWS += [(500 + i, "\n".join(f"## | * {rng.choice(VOCABULARY)} $ % #{rng.choice(VOCABULARY)} | & {rng.randint(0, 9999)}!" for _ in range(30)), "a") for i in range(6)]


@pytest.fixture(scope="module")
def folder(spark, tmp_path_factory):
    base = f"{tmp_path_factory.mktemp('tables')}"
    spark.createDataFrame([(*r, 7, "own", i) for i, r in enumerate(ROWS)], "doc_id long, text string, source string, n_words int, kept string, found int").repartition(3).write.parquet(f"{base}/documents.parquet")
    labels = [(r[0], 1) for r in ROWS[:40]] + [(500 + i, 0) for i in range(6)] + [(None, 1), (10, None)]
    spark.createDataFrame(labels, "doc_id long, quality int").write.parquet(f"{base}/labels.parquet")
    spark.createDataFrame(BENCH, "item_id long, text string").write.parquet(f"{base}/benchmark.parquet")
    return base


def test_pipeline_stage_by_stage(spark, folder):
    from tokenizers import Tokenizer

    docs = spark.read.parquet(f"{folder}/documents.parquet")
    schema, outputs = docs.schema, {}
    for name, stage in corpus_pipeline.STAGES:
        docs = outputs[name] = written(stage(spark, docs, folder), name)
        if name != "token_files":
            assert [(f.name, f.dataType) for f in docs.schema] == [(f.name, f.dataType) for f in schema]
            assert all(r.n_words == 7 and r.kept == "own" for r in docs.select("n_words", "kept").collect())
    taken = {n: [(r.doc_id, r.text, r.source) for r in d.collect()] for n, d in outputs.items() if n != "token_files"}

    crf = quality_rules.train(spark.read.parquet(f"{folder}/documents.parquet"), spark.read.parquet(f"{folder}/labels.parquet"))
    good = []
    for r in ROWS:
        c = quality_rules.text_counts((r[1] or "").encode())
        content = sum(k for k, s in zip(c["line_words"], crf.decode(c["lines"])) if not s) if c["n_words"] else 0
        if c["n_words"] >= 50 and 2 * c["n_repeat_words"] <= c["n_words"] and 2 * content >= c["n_words"]:
            good.append(r)
    assert Counter(taken["quality_rules"]) == Counter(good)
    assert {r[0] for r in good}.isdisjoint({400, 401, 402, 403, *range(500, 506)}) and {r[1] for r in good} >= set(CLEAN)

    prints = [print_of(r[1]) for r in good]
    group = list(range(len(good)))
    for _ in good:
        group = [min(group[j] for j in range(len(good)) if (prints[i] ^ prints[j]).bit_count() <= 2) for i in range(len(good))]
    one = [min((r for r, g in zip(good, group) if g == k), key=lambda r: (r[0] is None, r[0] or 0)) for k in sorted(set(group))]
    assert Counter((i, t) for i, t, _ in taken["near_duplicates"]) == Counter((i, t) for i, t, _ in one)

    grams = {tuple(plain(t)[k : k + 13]) for _, t in BENCH for k in range(len(plain(t)) - 12)}
    clean = []
    for r in taken["near_duplicates"]:
        w = plain(r[1])
        hit = {k + j for k in range(len(w) - 12) if tuple(w[k : k + 13]) in grams for j in range(13)}
        if not hit or 20 * len(hit) < len(w):
            clean.append(r)
    assert Counter(taken["decontamination"]) == Counter(clean) and not {r[0] for r in clean} & {300, 301, 302, 303}

    sizes, words = Counter(), Counter()
    for _, t, s in clean:
        sizes[s] += len(split(t))
    for _, t, s in taken["mixing"]:
        words[s] += len(split(t))
    target = {r.source: r.target for r in mixing.source_targets(outputs["decontamination"].withColumn("size", mixing.words_of(outputs["decontamination"].text))).collect()}
    assert set(taken["mixing"]) <= set(clean) and max(Counter(taken["mixing"]).values()) <= 3
    assert all(abs(words[s] - target[s]) <= 60 for s in sizes)

    t, want = Tokenizer.from_file(vocabulary_path()), Counter()
    for i, text, _ in taken["mixing"]:
        ids = np.array([*t.encode(text, add_special_tokens=False).ids, 0], "<u4")
        want[i, len(ids), zlib.crc32(ids.tobytes())] += 1
    last = outputs["token_files"].collect()
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in last) == want
    again = corpus_pipeline.run(spark, folder).collect()
    assert Counter((r.doc_id, r.n_tokens, r.ids_crc32) for r in again) == want


def test_pipeline_of_empty_tables(spark, folder, tmp_path):
    for name in ("documents", "labels", "benchmark"):
        spark.read.parquet(f"{folder}/{name}.parquet").limit(0).write.parquet(f"{tmp_path}/{name}.parquet")
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0
