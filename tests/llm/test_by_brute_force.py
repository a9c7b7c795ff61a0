"""Fingerprints, scores and languages against plain versions, text by text."""

from __future__ import annotations

import hashlib
import math
import re
import time
from collections import Counter, defaultdict

import numpy as np
import pyarrow as pa
import pytest
from conftest import SF
from pyspark.sql import functions as F

from tidegraph.llm import imatch, language_id, ppm, quality, textblocks, toxicity

ALL = (1 << 64) - 1
ODD_TEXTS = ["", None, "...", "a", "Ein Wort, ein WORT; ein-wort", "日本語 text", "x " * 400, "\x7f\x00 tab\tnew\nline", "1234 !!! 1234 !!!"]


def texts(spark, least: int, most: int) -> list[tuple[int, str | None, str]]:
    rows = spark.read.parquet(f"{SF}/documents.parquet").where(F.col("doc_id").between(least, most)).select("doc_id", "text", "lang").collect()
    return [tuple(r) for r in rows] + [(10**6 + least + i, t, "en") for i, t in enumerate(ODD_TEXTS)]


def frame(spark, rows):
    return spark.createDataFrame(rows, "doc_id bigint, text string, lang string")


def mix(x: int) -> int:
    for c in (0xFF51AFD7ED558CCD, 0xC4CEB9FE1A85EC53):
        x = (x ^ x >> 33) * c & ALL
    return x ^ x >> 33


def test_fingerprints(spark):
    how = imatch.IMatch(least_share=0.01)
    rows = sorted((i, t or "") for i, t, _ in texts(spark, 0, 300))
    shares = [(part, int(s)) for part, s in zip(how.subsets, textblocks.seeds(len(how.subsets), 21), strict=True)]

    def terms(text: str) -> set[bytes]:
        return set(re.findall(rb"[0-9A-Za-z\x80-\xff]+", text.encode().lower()))

    def code(term: bytes) -> int:
        return int(textblocks.range_code(textblocks.prefix_code(np.frombuffer(term, np.uint8)), np.array([0]), np.array([len(term)]))[0])

    met = Counter(t for _, text in rows for t in terms(text))
    lexicon = {t for t, n in met.items() if max(2, how.least_share * len(rows)) <= n <= how.most_share * len(rows)}
    assert len(lexicon) > 100

    def fields(text: str) -> list[int]:
        kept = terms(text) & lexicon or terms(text)  # without a term of the lexicon, all terms count
        codes, out = sorted(map(code, kept)), []
        for part, seed in shares:
            picked = [m for m in (mix(c ^ seed) for c in codes) if m <= min(part * 2.0**64, 2.0**64 - 2048)]
            out.append(sum(mix(m + k * 0x9E3779B97F4A7C15 & ALL) for k, m in enumerate(picked)) & ALL | 1 if picked else 0)
        return out

    def alike(a: list[int], b: list[int]) -> float:
        some = sum(1 for x, y in zip(a, b, strict=True) if x or y)
        return sum(1 for x, y in zip(a, b, strict=True) if x == y and x) / some if some else 1.0

    df = frame(spark, [(i, t, "") for i, t in rows])
    got = {r["doc_id"]: r for r in imatch.with_next(df, imatch.Lexicon.build(df, how), 3).collect()}
    assert len(got) == len(rows)
    for k, (i, t) in enumerate(rows):
        after = rows[(k + 1) % len(rows)][1]
        edited = t[: len(t) - len(t) // 2] + after[: len(t) // 2]
        a, b, c = fields(t), fields(edited), fields(after)
        r = got[i]
        assert r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert r["fingerprint"] == "".join(f"{x >> 32:08x}" for x in a) and r["edited_fingerprint"] == "".join(f"{x >> 32:08x}" for x in b)
        assert r["near_edited"] == pytest.approx(alike(a, b)) and r["near_next"] == pytest.approx(alike(a, c))


def test_quality_by_single_coordinates(spark):
    how = quality.Quality()
    rows = texts(spark, 0, 150)
    label = {i: int("o" in (t or "")[5:9]) for i, t, _ in rows}

    def spelt(text: str | None) -> list[bytes]:
        """Each n-gram as a text of its own; a word twice in a row is the same one for all words."""
        words = re.findall(rb"[0-9A-Za-z\x80-\xff]+|[^\x00-\x20\x7f0-9A-Za-z\x80-\xff]+", (text or "").encode().lower())
        return [*words, *(b"a a" if a == b else a + b" " + b for a, b in zip(words, words[1:], strict=False))]

    every = sorted({g for _, t, _ in rows for g in spelt(t)})
    spot, done = {}, 0
    for block in textblocks.blocks(pa.array([g.decode() for g in every])):
        ids, first = quality.ngrams(block, how.bits)
        spot.update((g, int(ids[a + (b" " in g)])) for g, a in zip(every[done : done + block.n], first, strict=False))
        done += block.n

    def grams(text: str | None) -> dict[int, float]:
        n = Counter(spot[g] for g in spelt(text))
        return {g: c * how.scale / n.total() for g, c in n.items()}

    z, n, z0, n0 = defaultdict(float), defaultdict(float), 0.0, 0.0

    def weight(g) -> float:
        return 0.0 if abs(z[g]) <= how.l1 else -(z[g] - math.copysign(how.l1, z[g])) / ((how.beta + math.sqrt(n[g])) / how.alpha + how.l2)

    def bias() -> float:
        return -z0 / ((how.beta + math.sqrt(n0)) / how.alpha)

    def chance(x: dict) -> float:
        return 1 / (1 + math.exp(-max(-35, min(35, bias() + sum(weight(g) * v for g, v in x.items())))))

    taught = sorted((i, grams(t)) for i, t, _ in rows if i % 3)
    for epoch in range(how.epochs):
        for k in np.random.default_rng(epoch).permutation(len(taught)):
            i, x = taught[k]
            miss = chance(x) - label[i]
            for g, v in x.items():
                step, w = miss * v, weight(g)
                z[g] += step - (math.sqrt(n[g] + step * step) - math.sqrt(n[g])) / how.alpha * w
                n[g] += step * step
            w0 = bias()
            z0 += miss - (math.sqrt(n0 + miss * miss) - math.sqrt(n0)) / how.alpha * w0
            n0 += miss * miss
    labels = spark.createDataFrame([(i, y) for i, y in label.items() if i % 3], "doc_id bigint, label int")
    model = quality.fit(frame(spark, rows), labels, how)
    got = {r["doc_id"]: r["score"] for r in quality.score(frame(spark, rows), model).collect()}
    assert np.std(list(got.values())) > 0.01
    assert got == pytest.approx({i: chance(grams(t)) for i, t, _ in rows}, abs=1e-4)


def test_toxicity_scores_by_single_grams(spark):
    how = toxicity.Toxicity(min_docs=2, epochs=3, segment=20)
    rows = texts(spark, 0, 150)
    labels = spark.createDataFrame([(i, int("o" in (t or "")[5:9])) for i, t, _ in rows], "doc_id bigint, label int")
    model = toxicity.fit(frame(spark, rows), labels, how)

    def chance(text: str | None) -> float:
        words, best = [], []
        for byte in [*(text or "").encode(), 32]:
            if toxicity._WORD[byte]:
                words[-1:] = [words[-1] + bytes([toxicity._FOLD[byte]])] if words else [bytes([toxicity._FOLD[byte]])]
            elif not words or words[-1]:
                words.append(b"")
        words = [w for w in words if w]
        for at in range(0, len(words), how.segment):
            held = []
            for w in words[at : at + how.segment]:
                marked = b"\0" + w + b"\0"
                for size in (3, 4, 5):
                    for k in range(len(marked) - size + 1):
                        spot = (int.from_bytes(marked[k : k + size]) + size) * 0x9E3779B97F4A7C15 & ALL
                        held.append(float(model.values[spot >> 64 - how.bits]))
            best.append(sum(held) / len(held))
        odds = model.intercept + max(best, default=0.0)
        return 1 / (1 + math.exp(-max(-35, min(35, odds))))

    got = {r["doc_id"]: r["score"] for r in toxicity.score(frame(spark, rows), model).collect()}
    assert np.std(list(got.values())) > 0.01
    assert got == pytest.approx({i: chance(t) for i, t, _ in rows}, abs=1e-5)


def test_toxicity_training_by_single_grams(spark):
    how = toxicity.Toxicity(bits=14, dim=3, min_docs=3, epochs=3, segment=20, batch=16)
    rows = sorted(texts(spark, 0, 100))
    labels = [int("o" in (t or "")[5:9]) for _, t, _ in rows]
    model = toxicity.fit(frame(spark, rows), spark.createDataFrame([(r[0], y) for r, y in zip(rows, labels, strict=True)], "doc_id bigint, label int"), how)

    def grams(word: bytes) -> list[int]:
        marked = b"\0" + word + b"\0"
        keys = [int.from_bytes(marked[k : k + size]) + size for size in (3, 4, 5) for k in range(len(marked) - size + 1)]
        return [(key * 0x9E3779B97F4A7C15 & ALL) >> 64 - how.bits for key in keys]

    # by document and segment
    docs = []
    for _, t, _ in rows:
        held = [grams(w) for w in re.findall(rb"[0-9a-z\x80-\xff]+", (t or "").encode().lower())]
        docs.append([sum(held[at : at + how.segment], []) for at in range(0, len(held), how.segment)])
    rng = np.random.default_rng(how.seed)
    spare = rng.random(len(docs)) < how.kept_back
    used, kept = np.flatnonzero(~spare), np.flatnonzero(spare)
    met = Counter(g for d in used for g in set(sum(docs[d], [])))
    start = rng.normal(0, 0.01, (1 << how.bits, how.dim))
    table = {g: start[g] for g, n in met.items() if n >= how.min_docs}
    top = rng.normal(0, 1, (how.dim, 2))
    top /= np.linalg.norm(top[:, 1] - top[:, 0])
    prior = (sum(labels[d] for d in used) + 1) / (len(used) + 2)
    bias = np.array([0.0, math.log(prior / (1 - prior))])

    def gain(held: list[int]) -> float:
        return how.scale * sum(float(table[g] @ (top[:, 1] - top[:, 0])) for g in held if g in table) / len(held)

    for epoch in range(how.epochs):
        order, rate = rng.permutation(used), how.rate * (1 - epoch / how.epochs)
        for lo in range(0, len(order), how.batch):
            part = [d for d in order[lo : lo + how.batch] if docs[d]]
            step, step_top, step_bias = defaultdict(lambda: np.zeros(how.dim)), np.zeros_like(top), np.zeros(2)
            for d in part:
                held = max(docs[d], key=gain) if epoch else sum(docs[d], [])
                hidden = how.scale * sum((table[g] for g in held if g in table), np.zeros(how.dim)) / len(held)
                chance = np.exp(hidden @ top + bias)
                error = (chance / chance.sum() - np.eye(2)[labels[d]]) * (0.5 / (prior if labels[d] else 1 - prior))
                for g in held:
                    if g in table:
                        step[g] += top @ error * how.scale / len(held)
                step_top += np.outer(hidden, error)
                step_bias += error
            for g, by in step.items():
                table[g] = table[g] - rate * (by + how.decay * table[g])
            top -= rate * 0.1 * step_top / len(part)
            bias -= rate * 0.1 * step_bias / len(part)
    want = np.zeros(1 << how.bits)
    for g, row in table.items():
        want[g] = how.scale * (row @ (top[:, 1] - top[:, 0]))
    assert 100 < len(table) < (1 << how.bits) - 100 and np.std(want) > 0.01
    assert model.values == pytest.approx(want, abs=1e-3)
    odds = sorted((float(bias[1] - bias[0]) + max(map(gain, docs[d]), default=0.0), labels[d]) for d in kept)
    wrong = [sum(y for _, y in odds[:cut]) + sum(1 - y for _, y in odds[cut:]) for cut in range(len(odds) + 1)]
    best = [cut for cut, n in enumerate(wrong) if n == min(wrong)]
    edges = [odds[0][0] - 1, *(o for o, _ in odds), odds[-1][0] + 1]
    mid = best[len(best) // 2]
    assert model.intercept == pytest.approx(float(bias[1] - bias[0]) - (edges[mid] + edges[mid + 1]) / 2, abs=1e-3)


def test_toxicity_training_does_not_read_the_table_by_document():
    texts = [f"wurst {i % 7} weather {i % 11} today" for i in range(800)]

    def seconds(n: int, bits: int) -> float:
        how = toxicity.Toxicity(bits=bits)
        bags, labels = toxicity.WordBags(pa.chunked_array([texts[:n]]), how), np.arange(n) % 2
        before = time.process_time()
        toxicity.ToxicityModel(how).fit(bags, labels)
        return time.process_time() - before

    # what 700 documents more take in a large table, and in a small one
    assert seconds(800, 20) - seconds(100, 20) < 3 * (seconds(800, 12) - seconds(100, 12)) + 1


def test_languages_by_plain_tries(spark):
    how = language_id.LanguageId()
    rows = [r for r in texts(spark, 0, 120) if len(r[1] or "") < 3000]
    fold = lambda t: bytes(language_id.FOLD[list((t or "").encode())])
    tries = {}
    for i, t, lang in rows:
        if i % 3 != 1 and t is not None and lang is not None:
            tries.setdefault(lang, ppm.AdaptiveTrie(how.order)).code(fold(t))
    model = language_id.fit(frame(spark, rows), F.col("doc_id") % 3 != 1, how)
    names = sorted(tries)
    assert len(names) > 2
    for r in language_id.identify(frame(spark, rows), model).collect():
        if not any(c.isalpha() for c in r["text"] or ""):
            assert (r["lang_pred"], r["score"]) == ("und", 0.0)
            continue
        bits = [tries[x].code(fold(r["text"]), update=False) for x in names]
        assert r["lang_pred"] == names[int(np.argmin(bits))]
        assert r["score"] == pytest.approx(1 / sum(2.0 ** max(min(bits) - b, -1000) for b in bits), abs=1e-3)
