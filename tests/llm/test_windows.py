import hashlib
import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockgraph.llm import _windows, substring_dedup, suffix_dedup
from blockgraph.llm.suffix_dedup import deep_shallow


def docs_frame(spark, rows, extra=False):
    df = spark.createDataFrame(rows, "doc_id long, text string")
    return df.withColumns({c: F.lit(1) for c in ("first", "key", "said", "n", "kept", "bucket")}) if extra else df


def brute_words(rows, length):
    seen, out = {}, {}
    docs = sorted((d, (t or "").encode().split()) for d, t in rows if d is not None)
    for d, words in docs:
        for i in range(len(words) - length + 1):
            seen.setdefault(tuple(words[i : i + length]), (d, i))
    for d, words in docs:
        gone = [False] * len(words)
        for i in range(len(words) - length + 1):
            if seen[tuple(words[i : i + length])] != (d, i):
                gone[i : i + length] = [True] * length
        kept = b" ".join(w for w, g in zip(words, gone) if not g)
        out[d] = (len(words), sum(gone), hashlib.sha256(kept).hexdigest())
    return out


def brute_bytes(rows, length):
    from collections import Counter

    docs = [(d, (t or "").encode()) for d, t in rows if d is not None]
    seen = Counter(t[i : i + length] for _, t in docs for i in range(len(t) - length + 1))
    out = {}
    for d, t in docs:
        gone = np.zeros(len(t) + 2, bool)
        for i in range(len(t) - length + 1):
            if seen[t[i : i + length]] > 1:
                gone[i + 1 : i + 1 + length] = True
        spans = int((np.diff(gone.astype(int)) == 1).sum())
        kept = bytes(np.frombuffer(t, np.uint8)[~gone[1:-1]])
        out[d] = (len(t), int(gone.sum()), spans, hashlib.sha256(kept).hexdigest())
    return out


def planted(seed, n=60, words=120, vocabulary=4000):
    rnd = random.Random(seed)
    word = lambda: "".join(rnd.choice("abcdé") for _ in range(rnd.randint(1, 6))) + str(rnd.randrange(vocabulary))
    shared = [" ".join(word() for _ in range(rnd.randint(18, 60))) for _ in range(6)]
    rows = []
    for d in range(n):
        parts = [word() for _ in range(rnd.randrange(words))]
        for _ in range(rnd.randrange(4)):
            parts.insert(rnd.randrange(len(parts) + 1), rnd.choice(shared))
        if rnd.random() < 0.2:
            parts.insert(0, "x " * rnd.randrange(80) + "\n\t" + "ab" * rnd.randrange(300))
        rows.append((d, rnd.choice([" ", "  ", "\n"]).join(parts)))
    for d in range(n, n + 12):
        base = rows[rnd.randrange(8)][1].split(" ")
        if base and rnd.random() < 0.7:
            base[rnd.randrange(len(base))] = word()
        rows.append((d, " ".join(base)))
    return rows + [(1000, None), (1001, ""), (1002, "one"), (1003, "aaaa " * 400), (1004, "aaaa " * 100), (None, "lost " * 50)]


@pytest.mark.parametrize("seed", [1, 2])
def test_words_match_brute_force(spark, seed):
    rows = planted(seed)
    got = substring_dedup.digest(substring_dedup.repeated_words(docs_frame(spark, rows, extra=seed == 2))).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got} == brute_words(rows, 20)


@pytest.mark.parametrize("seed", [1, 2])
def test_bytes_match_brute_force(spark, seed):
    rows = planted(seed)
    got = suffix_dedup.digest(suffix_dedup.repeated_bytes(docs_frame(spark, rows, extra=seed == 2))).collect()
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == brute_bytes(rows, 200)


def test_given_documents_match_brute_force(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = substring_dedup.digest(substring_dedup.repeated_words(docs)).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got} == brute_words(rows, 20)
    got = suffix_dedup.digest(suffix_dedup.repeated_bytes(docs)).collect()
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == brute_bytes(rows, 200)


@pytest.mark.parametrize("seed", [1, 2])
def test_crowded_minimisers_change_nothing(spark, monkeypatch, seed):
    """Every second minimiser counts as crowded, and buckets and parts are many and small."""
    bits = np.random.default_rng(seed).integers(0, 256, _windows.SLOTS // 8, np.uint8)
    monkeypatch.setattr(_windows, "crowded", lambda *_: _windows.Crowd(bits))
    monkeypatch.setattr(_windows, "BUCKET_BYTES", 1 << 13)
    monkeypatch.setattr(_windows, "PART_BYTES", 1 << 12)
    rows = planted(seed)
    got = substring_dedup.digest(substring_dedup.repeated_words(docs_frame(spark, rows))).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got} == brute_words(rows, 20)
    got = suffix_dedup.digest(suffix_dedup.repeated_bytes(docs_frame(spark, rows))).collect()
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == brute_bytes(rows, 200)


def test_crowded_minimisers_are_found(spark, monkeypatch):
    monkeypatch.setattr(_windows, "SAMPLE_ONE_IN", 1)
    monkeypatch.setattr(_windows, "CROWDED_BYTES", 4000)
    windows = _windows.Windows(20, 4, words=True)
    texts = [" ".join([*(f"a{d}x{i}" for i in range(30)), *(f"s{i}" for i in range(20)), *(f"b{d}x{i}" for i in range(30))]) for d in range(40)]
    rows = spark.createDataFrame([(d, 0, t) for d, t in enumerate(texts)], "doc_id long, key long, text string")
    crowd = _windows.crowded(spark, rows, windows)
    load = {}
    for t in texts:
        for values, strings, *_ in windows.strings(t.encode()):
            for v, s in zip(values.tolist(), strings, strict=True):
                load[v] = load.get(v, 0) + len(s)
    assert {v for v, n in load.items() if n > 4000} == {v for v in load if crowd.holds(np.array([v], np.uint64))[0]} != set()
    monkeypatch.setattr(_windows, "CROWDED_BYTES", 1 << 30)
    assert _windows.crowded(spark, rows, windows) is None


def test_long_texts_match_brute_force(spark):
    """Texts far above the others, over several segments, with repeats inside and across."""
    rnd = random.Random(3)
    base = "".join(rnd.choice("abcdefgh ") for _ in range(30_000))
    rows = [(1, base + "tail one"), (2, base[500:20_000] + " " + base[:900]), (3, "z" * 5000)]
    got = suffix_dedup.digest(suffix_dedup.repeated_bytes(docs_frame(spark, rows))).collect()
    assert {r["doc_id"]: (r["n_bytes"], r["n_removed"], r["n_spans"], r["kept_sha256"]) for r in got} == brute_bytes(rows, 200)
    got = substring_dedup.digest(substring_dedup.repeated_words(docs_frame(spark, rows))).collect()
    assert {r["doc_id"]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in got} == brute_words(rows, 20)


def test_repeated_rows_and_empty_table(spark):
    text = " ".join(f"w{i}" for i in range(60))
    rows = [(1, text), (1, text), (2, text)]
    got = substring_dedup.repeated_words(docs_frame(spark, rows)).orderBy("doc_id").collect()
    assert [r["kept_text"] for r in got] == [text, text, ""]
    got = suffix_dedup.repeated_bytes(docs_frame(spark, rows[:2])).collect()
    assert [bytes(r["kept"]) for r in got] == [b"", b""]
    assert substring_dedup.repeated_words(docs_frame(spark, [])).count() == 0
    assert suffix_dedup.repeated_bytes(docs_frame(spark, [])).count() == 0


@pytest.mark.parametrize("shallow", [0, 8, 48])
def test_deep_shallow_sorts(shallow):
    rnd = random.Random(5)
    suffixes = [bytes(rnd.choice(b"ab") for _ in range(rnd.randrange(60))) for _ in range(300)]
    suffixes += [b"ab" * 40 + bytes([rnd.randrange(4)]) * rnd.randrange(6) for _ in range(200)] + [b"", b""]
    assert deep_shallow(suffixes, shallow) == sorted(range(len(suffixes)), key=lambda k: (suffixes[k], k))
