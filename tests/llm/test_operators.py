import random
import re

import numpy as np
import pytest
from pyspark.sql import functions as F

from blockgraph.llm import chat_format, decontamination, language_id, line_dedup, near_dedup, packing, token_counts, top_k
from blockgraph.llm._components import components

WORD = re.compile(rb"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string"
CLASH = ("bucket", "root", "node", "label", "length", "bin", "key", "said", "n", "first", "a", "b", "__x")


def frame(spark, rows, clash=True):
    df = spark.createDataFrame(rows, SCHEMA)
    return df.withColumns({c: F.lit("x") for c in CLASH}) if clash else df


def words(rnd, n, pool):
    return " ".join(rnd.choice(pool) for _ in range(n))


@pytest.fixture(scope="module")
def pool():
    rnd = random.Random(3)
    return ["".join(rnd.choice("abcdefghij") for _ in range(rnd.randint(2, 8))) for _ in range(3000)]


# language identification


def test_language_on_held_out_rows(spark, sf):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    got = language_id.identify(spark, docs).join(docs.select("doc_id", "lang"), "doc_id").where("held_out").collect()
    assert len(got) > 20 and sum(r["lang"] == r["lang_pred"] for r in got) >= 0.95 * len(got)


def test_language_edge_cases(spark):
    rows = [(1, "the cat and the dog", "en", "s"), (3, "le chat et le chien", "fr", "s"), (4, None, "en", None), (5, "123 ...", "fr", "s"), (6, "", None, "s"), (7, "the the dog", None, "s"), (7, "the the dog", None, "s"), (None, "le chien", "fr", "s")]
    rows += [(100 + k, t, lang, "s") for k in range(60) for t, lang in (("the cat and the dog", "en"), ("le chat et le chien", "fr"))]
    got = {(r["doc_id"], r["lang_pred"], 0 <= r["score"] <= 1) for r in language_id.identify(spark, frame(spark, rows)).collect()}
    assert {(4, "und", True), (5, "und", True), (6, "und", True), (7, "en", True), (None, "fr", True)} <= got
    assert language_id.identify(spark, frame(spark, [])).count() == 0
    assert {r["lang_pred"] for r in language_id.identify(spark, frame(spark, [(1, "some text", None, "s")])).collect()} == {"und"}
    kept = language_id.confident(spark, frame(spark, rows))
    assert kept.columns == frame(spark, rows).columns and kept.where("doc_id IS NULL OR doc_id IN (4, 5, 6)").count() == 0


def test_language_equals_a_plain_twin(spark):
    """A dictionary-based naive Bayes over the same hashed n-grams, one n-gram at a time."""
    rnd = random.Random(9)
    letters = {"": "xyzw ", "aa": "abcde ", "bb": "abfgh ", "cc": "éñü a"}
    make = lambda lang, n: "".join(rnd.choice(letters[lang]) for _ in range(n))
    rows = [(k, make(lang, rnd.randrange(1, 60)), lang, "s") for k in range(90) for lang in [rnd.choice(list(letters))]]
    rows += [(200, "ab é" * 3000, "aa", "s"), (201, "a", None, "s"), (202, "qqq", "bb", "s"), (203, "7", "aa", "s")]
    buckets = language_id.BUCKETS

    def grams(text):
        codes = np.frombuffer(f" {text.lower()} ".encode("utf-32-le"), np.uint32).astype(np.uint64)
        return [int(language_id._bucket_ids(codes[i : i + n], n, buckets)[0]) for n in language_id.ORDERS for i in range(len(codes) - n + 1)]

    import zlib

    lettered = lambda t: any(c.isalpha() for c in t or "")
    counts = {lang: {} for lang in letters}
    for d, t, lang, _ in rows:
        if lang is not None and lettered(t) and zlib.crc32(str(d).encode()) % 4 != 2:
            for g in grams(t):
                counts[lang][g] = counts[lang].get(g, 0) + 1
    totals = {lang: sum(c.values()) + 0.5 * buckets for lang, c in counts.items()}
    want = {}
    for d, t, *_ in rows:
        if not lettered(t):
            want[d] = ("und", 0.0)
            continue
        sums = {lang: sum(np.log((counts[lang].get(g, 0) + 0.5) / totals[lang]) for g in grams(t)) for lang in sorted(letters)}
        best = max(sorted(sums), key=sums.get)
        want[d] = (best, 1 / sum(np.exp(x - sums[best]) for x in sums.values()))
    got = {r["doc_id"]: (r["lang_pred"], r["score"], r["held_out"]) for r in language_id.identify(spark, frame(spark, rows).withColumns({c: F.lit(1) for c in ("row", "said")})).collect()}
    assert set(got) == set(want) and {g[0] for g in got.values()} == {"und", *letters}
    for d, (lang, score) in want.items():
        assert got[d][0] == lang and abs(got[d][1] - score) < 1e-3 and got[d][2] == (zlib.crc32(str(d).encode()) % 4 == 2)


def test_long_texts_count_like_short_ones(monkeypatch):
    text, table = "le chat noir " * 50, np.random.default_rng(0).normal(size=(language_id.BUCKETS, 3)).astype(np.float32)
    whole = language_id._log_odds([text, "b", text], table, language_id.BUCKETS)
    monkeypatch.setattr(language_id, "CHUNK_CHARS", 17)
    assert np.allclose(whole, language_id._log_odds([text, "b", text], table, language_id.BUCKETS), rtol=1e-4)


# token counts


def test_token_counts_match_the_library(spark, sf):
    import sentencepiece

    model = sentencepiece.SentencePieceProcessor(model_file=token_counts.default_model())
    odd = ["", None, " ", "a  b", "  x", "x ", "a\nb c", "x▁y z", "é" * 50, "w " * 5000, "<s> hi </s>", "　a"]
    rows = [(k, t, None, None) for k, t in enumerate(odd)] + [(0, "", None, None)]
    rows += [(100 + r["doc_id"], r["text"], None, None) for r in spark.read.parquet(f"{sf}/documents.parquet").limit(40).collect()]
    got = token_counts.token_counts(frame(spark, rows)).collect()
    want = sorted((d, len((t or "").encode()), len(model.encode(t or "")), len(model.encode(t or "")) > 4096) for d, t, *_ in rows)
    assert sorted((r["doc_id"], r["n_bytes"], r["n_tokens"], r["over_limit"]) for r in got) == want
    assert token_counts.token_counts(frame(spark, [])).count() == 0


@pytest.mark.parametrize("limit", [1, 5, 40])
def test_safe_parts_add_up(limit):
    rnd = random.Random(limit)
    text = "".join(rnd.choice(["a", "b ", "  ", " ", "\n", "▁", "é", "the ", "x▁ ", "\t"]) for _ in range(2000))
    model = token_counts.default_model()
    assert sum(token_counts.count_texts(token_counts.safe_parts(text, limit), model)) == token_counts.count_texts([text], model)[0]


# line dedup


def brute_lines(rows, run=2):
    docs = {d: (t or "").split("\n") if t else [] for d, t, *_ in rows}
    full = {d: [k for k, x in enumerate(lines) if x.strip(" ")] for d, lines in docs.items()}
    first, out = {}, {}
    for d in sorted(docs):
        for i in range(len(full[d]) - run + 1):
            first.setdefault(tuple(docs[d][k] for k in full[d][i : i + run]), (d, i))
    for d, lines in docs.items():
        gone = set()
        for i in range(len(full[d]) - run + 1):
            if first[tuple(lines[k] for k in full[d][i : i + run])] != (d, i):
                gone |= set(full[d][i : i + run])
        out[d] = (len(lines), sorted(gone), "\n".join(x for k, x in enumerate(lines) if k not in gone))
    return out


def line_rows(seed=1):
    rnd = random.Random(seed)
    lines = [f"line {k} of words" for k in range(25)]
    rows = [(d, "\n".join(rnd.choice([*lines, "", "   ", f"own {d}"]) for _ in range(rnd.randrange(12))), "en", "s") for d in range(80)]
    return rows + [(200, "x\n" * 50, "en", "s"), (201, "alone", "en", "s"), (202, "\n\n\n", "en", "s")]


def test_lines_match_brute_force(spark):
    rows = line_rows()
    got = {r["doc_id"]: (r["n_lines"], r["removed"], r["kept_text"]) for r in line_dedup.dedup_lines(frame(spark, rows)).collect()}
    assert got == brute_lines(rows)


def brute_long_lines(rows, words):
    """Line numbers of later copies of lines with at least so many words, for each document."""
    seen, out = set(), {}
    for d, t, *_ in sorted(rows):
        out[d] = set()
        for k, line in enumerate((t or "").split("\n")):
            if len(line.encode().split()) >= words:
                out[d] |= {k} if line in seen else set()
                seen.add(line)
    return out


def test_long_lines_go_alone(spark, sf):
    told = "one two three four five six seven eight"
    rows = line_rows() + [(300, told, "en", "s"), (301, told, "en", "s"), (302, f"own\n\n{told}\nelse\n{told} nine\n{told}", "en", "s"), (303, "one two three four", "en", "s"), (304, "one two three four", "en", "s"), (305, f"{told} nine\tten", "en", "s"), (306, f"x\n{told}  nine\nelse\n{told} nine", "en", "s")]
    rows += [(1000 + r["doc_id"], r["text"], "en", "s") for r in spark.read.parquet(f"{sf}/documents.parquet").collect()]
    got = {r["doc_id"]: (r["n_lines"], r["removed"], r["kept_text"]) for r in line_dedup.dedup_lines(frame(spark, rows), long_words=line_dedup.LONG_WORDS).collect()}
    runs, alone, text = brute_lines(rows), brute_long_lines(rows, line_dedup.LONG_WORDS), {d: t for d, t, *_ in rows}
    want = {}
    for d, (n, gone, _) in runs.items():
        gone = sorted({*gone, *alone[d]})
        want[d] = (n, gone, "\n".join(x for k, x in enumerate((text[d] or "").split("\n")) if k not in gone) if text[d] is not None else None)
    assert got == want
    assert [got[d][1] for d in (300, 301, 302, 303, 304)] == [[], [0], [2, 5], [], []]
    assert 301 not in {r["doc_id"] for r in line_dedup.without_repeats(frame(spark, rows), long_words=line_dedup.LONG_WORDS).select("doc_id").collect()}


def test_line_edge_cases(spark):
    rows = [(1, "a b\nc d\ne", "en", "s"), (1, "a b\nc d\ne", "en", "s"), (2, "x\na b\nc d", "en", "s"), (3, None, None, None), (None, "a b\nc d", "en", "s"), (4, "a b\nc d", "en", "s")]
    got = sorted((r["doc_id"], r["kept_text"]) for r in line_dedup.dedup_lines(frame(spark, rows)).where("doc_id <> 3").collect())
    assert got == [(1, "a b\nc d\ne"), (1, "a b\nc d\ne"), (2, "x"), (4, "")]
    kept = line_dedup.without_repeats(frame(spark, rows))
    assert kept.columns == frame(spark, rows).columns
    assert sorted((r["doc_id"] or -1, r["text"]) for r in kept.where("text IS NOT NULL").collect()) == [(-1, "a b\nc d"), (1, "a b\nc d\ne"), (1, "a b\nc d\ne"), (2, "x")]
    assert kept.where("text IS NULL").count() == 1
    assert line_dedup.dedup_lines(frame(spark, [])).count() == 0


def test_lines_stay_out_of_python(spark, sf):
    plan = line_dedup.dedup_lines(spark.read.parquet(f"{sf}/documents.parquet"))._jdf.queryExecution().executedPlan().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


# near duplicates


def brute_near(rows):
    low = bytes(range(65)) + bytes(range(97, 123)) + bytes(range(91, 256))
    sets, root = {}, {}
    for d, t, *_ in rows:
        w = WORD.findall((t or "").encode().translate(low))
        sets[d] = frozenset(tuple(w[k : k + 5]) for k in range(len(w) - 4)) if len(w) >= 5 else frozenset([tuple(w)] if w else [])
        root[d] = d
    find = lambda x: x if root[x] == x else find(root[x])
    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            n = len(sets[a] & sets[b])
            if n and 100 * n >= 75 * (len(sets[a]) + len(sets[b]) - n):
                x, y = sorted((find(a), find(b)))
                root[y] = x
    return {d: (len(sets[d]), find(d)) for d in ids}


def near_rows(pool, seed=2):
    rnd = random.Random(seed)
    rows = []
    for base in range(12):
        text = words(rnd, rnd.choice([3, 8, 60, 150]), pool).split()
        for copy in range(rnd.randrange(1, 14)):
            new = list(text)
            for _ in range(rnd.randrange(0, 1 + len(text) // 12)):
                new[rnd.randrange(len(new))] = rnd.choice(pool)
            rows.append((len(rows), (" ".join(new)).title() if copy % 3 == 0 else "  ".join(new), "en", "s"))
    rows += [(500, None, None, None), (501, "", "en", "s"), (502, " \n", "en", "s"), (503, "one two", "en", "s"), (504, "ONE  two", "en", "s")]
    return rows


@pytest.mark.parametrize("block", [1024, 4])
def test_near_matches_brute_force(spark, pool, block):
    rows = near_rows(pool)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicates(spark, frame(spark, rows), block).collect()}
    assert got == brute_near(rows)


@pytest.mark.parametrize("block", [3, 1024])
def test_near_chains_of_different_texts(spark, pool, block):
    """A template that all share chains them into one cluster; only neighbours of a chain of small edits are linked."""
    rnd, rows = random.Random(12), []
    template = words(rnd, 60, pool).split()
    for k in range(12):
        rows.append((k, " ".join(template + words(rnd, 70, pool).split()), "en", "s"))
    text = words(rnd, 200, pool).split()
    for k in range(25):
        rows.append((100 + k, " ".join(text), "en", "s"))
        for _ in range(4):
            text[rnd.randrange(len(text))] = rnd.choice(pool)
    rnd.shuffle(rows)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in near_dedup.near_duplicates(spark, frame(spark, rows), block).collect()}
    assert got == brute_near(rows)


def test_near_texts_that_meet_nobody_are_not_shuffled(spark):
    """All chosen rows pass the bitmap and next to no others do, also at its ends."""
    from pyspark.sql import functions as F

    rows = spark.range(-2000, 200_000).select(F.col("id").alias("node"), F.xxhash64("id").alias("key"), F.lit("x").alias("text"))
    chosen = rows.where("node % 7 = 0").select("node", "key")
    got = near_dedup.likely(rows, chosen)
    want = chosen.count()
    assert got.columns == rows.columns and got.join(chosen, ["node", "key"]).count() == want
    assert want <= got.count() < want + 2000
    assert near_dedup.likely(rows, chosen.limit(0)).count() == 0


def test_near_edge_cases(spark, pool):
    rnd = random.Random(4)
    text = words(rnd, 40, pool)
    rows = [(5, text, "en", "s"), (5, text, "en", "s"), (5, words(rnd, 40, pool), "en", "s"), (9, text, "en", "s"), (None, text, "en", "s")]
    got = sorted((r["doc_id"], r["component_id"]) for r in near_dedup.near_duplicates(spark, frame(spark, rows)).collect())
    assert got == [(5, 5), (5, 5), (5, 5), (9, 5)]
    rows = [(3, text, "en", "s"), (5, words(rnd, 40, pool), "en", "s"), (5, text, "en", "s"), (8, None, "en", "s"), (8, words(rnd, 40, pool), "en", "s"), (9, words(rnd, 6000, pool), "en", "s")]
    got = sorted((r["doc_id"], r["component_id"], r["n_shingles"]) for r in near_dedup.near_duplicates(spark, frame(spark, rows)).collect())
    assert [g[:2] for g in got] == [(3, 3), (5, 3), (5, 3), (8, 8), (8, 8), (9, 9)] and got[-1][2] == 5996
    rows = [(5, text, "en", "s"), (5, text, "en", "s"), (5, words(rnd, 40, pool), "en", "s"), (9, text, "en", "s"), (None, text, "en", "s")]
    assert near_dedup.near_duplicates(spark, frame(spark, [])).count() == 0
    kept = near_dedup.one_of_each(spark, frame(spark, rows))
    assert kept.columns == frame(spark, rows).columns and [r["doc_id"] for r in kept.collect()] == [5]


def test_components(spark):
    rnd = random.Random(1)
    edges = [(k, k + 1) for k in range(30)] + [(rnd.randrange(100, 160), rnd.randrange(100, 160)) for _ in range(40)] + [(7, 7)]
    root = {v: v for e in edges for v in e}
    find = lambda x: x if root[x] == x else find(root[x])
    for a, b in edges:
        x, y = sorted((find(a), find(b)))
        root[y] = x
    got = {r["node"]: r["root"] for r in components(spark.createDataFrame(edges, "a long, b long")).collect()}
    assert got == {v: find(v) for e in edges for v in e if e[0] != e[1]}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


# decontamination


def edit_within(item, text, limit):
    """Least edit distance of item to a passage of text, by full dynamic programming."""
    row = np.zeros(len(text) + 1, int)
    for i, w in enumerate(item, 1):
        new = np.minimum(row[:-1] + np.array([w != x for x in text], int), row[1:] + 1)
        new = np.concatenate(([i], new))
        row = np.minimum.accumulate(new - np.arange(len(new))) + np.arange(len(new))
    return int(row.min())


def edited(rnd, item, edits, pool):
    out = list(item)
    for _ in range(edits):
        k = rnd.randrange(len(out))
        kind = rnd.randrange(3)
        if kind == 0:
            out[k] = rnd.choice(pool)
        elif kind == 1:
            del out[k]
        else:
            out.insert(k, rnd.choice(pool))
    return out


def test_leaks_match_brute_force(spark, pool):
    rnd = random.Random(8)
    items = [words(rnd, n, pool).split() for n in (1, 3, 6, 14, 25, 40, 59)]
    rows = []
    for d in range(120):
        text = words(rnd, rnd.randrange(5, 60), pool).split()
        if d % 2:
            item = items[d % len(items)]
            text[3:3] = edited(rnd, item, rnd.randrange(0, int(len(item) * 0.25) + 1), pool)
        rows.append((d, " ".join(text).upper() if d % 5 == 0 else ", ".join(text), "en", "s"))
    rows += [(300, None, None, None), (301, "", "en", "s"), (301, "", "en", "s")]
    bench = spark.createDataFrame([(k, " ".join(i)) for k, i in enumerate(items)] + [(50, None), (51, ""), (None, "x y z")], "item_id long, text string")
    got = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontamination.contaminated(spark, frame(spark, rows), bench).collect()}
    want = {}
    for d, t, *_ in rows:
        text = re.findall(r"[^\W_]+", (t or "").lower())
        for k, item in enumerate(items):
            if text and (e := edit_within(item, text, 99)) <= decontamination.allowed_edits(len(item), 0.2):
                want[d, k] = e
    assert set(got) <= set(want) and len(got) >= 0.97 * len(want)
    assert all(d in got or want[d] for d in want)
    assert all(got[p] == want[p] for p in got)
    clean = decontamination.clean(spark, frame(spark, rows), bench)
    assert {r["doc_id"] for r in clean.collect()} == {d for d, *_ in rows} - {d for d, _ in got}
    blocks = {(r["doc_id"], r["item_id"]): r["distance"] for r in decontamination.contaminated(spark, frame(spark, rows), bench, block_bytes=200).collect()}
    assert decontamination.item_blocks(bench, 200)[0] > 2 and blocks == got
    assert {r["doc_id"] for r in decontamination.clean(spark, frame(spark, rows), bench, block_bytes=200).collect()} == {r["doc_id"] for r in clean.collect()}
    assert decontamination.contaminated(spark, frame(spark, []), bench).count() == 0
    assert decontamination.contaminated(spark, frame(spark, rows), bench.limit(0)).count() == 0


def test_closest_passage_ties(pool):
    """Least distance; among equals the earliest end, then the latest start: against every passage of the text."""
    rnd = random.Random(4)
    for _ in range(60):
        item, text = ([rnd.randrange(4) for _ in range(rnd.randrange(1, n))] for n in (7, 14))
        far = lambda a, b: edit_exact(item, text[a:b])
        distance, end, start = min((far(a, b), b, -a) for b in range(len(text) + 1) for a in range(b + 1))
        got = decontamination.closest_passage(np.array(item, np.uint64), np.array(text, np.uint64), 6)
        assert got[0] == distance and (distance > 6 or got == (distance, -start, end)), (item, text)


def edit_exact(a, b):
    row = list(range(len(b) + 1))
    for i, x in enumerate(a, 1):
        new = [i]
        for j, y in enumerate(b, 1):
            new.append(min(row[j - 1] + (x != y), row[j] + 1, new[-1] + 1))
        row = new
    return row[-1]


def test_long_text_holds_an_item_at_its_end(spark, pool):
    rnd = random.Random(5)
    item = words(rnd, 20, pool)
    long = words(rnd, 60_000, pool)
    bench = spark.createDataFrame([(1, item)], "item_id long, text string")
    got = decontamination.contaminated(spark, frame(spark, [(1, long, "en", "s"), (2, f"{long} {item}", "en", "s")]), bench).collect()
    assert [(r["doc_id"], r["start"], r["distance"]) for r in got] == [(2, 60_000, 0)]


# top-k


def brute_top(vectors, k, every):
    clean = {}
    for i, v in vectors:
        if i is not None and v and all(x is not None and np.isfinite(x) for x in v):
            w = [int(np.floor(1024 * float(x))) for x in v]
            clean[i] = min(clean.get(i, w), w)
    sizes = [len(v) for v in clean.values()]
    dims = max(set(sizes), key=lambda s: (sizes.count(s), s)) if sizes else 0
    clean = {i: v for i, v in clean.items() if len(v) == dims}
    out = {}
    for q in clean:
        if q % every == 0:
            scored = sorted((-sum(a * b for a, b in zip(clean[q], v)), i) for i, v in clean.items() if i != q)[:k]
            out |= {(q, r + 1): (i, -s) for r, (s, i) in enumerate(scored)}
    return out


@pytest.mark.parametrize("bands", [None, 7])
def test_top_k_matches_brute_force(spark, bands, monkeypatch):
    if bands:
        monkeypatch.setattr(top_k, "BLOCK", 40)
        monkeypatch.setattr(top_k, "QUERY_BLOCK", 5)
    rng = np.random.default_rng(1)
    rows = [(int(i), [float(x) for x in v]) for i, v in enumerate(rng.normal(size=(300, 8)) * rng.exponential(1, (300, 1)))]
    rows += [(400 + i, rows[3][1]) for i in range(20)] + [(500, None), (501, []), (502, [1.0] * 7 + [None]), (503, [float("nan")] * 8), (504, [1.0] * 9), (20, [9.0] * 8), (None, [1.0] * 8), (505, [0.0] * 8)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumns({c: F.lit(1) for c in ("band", "block", "floor", "v", "score")})
    got = {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in top_k.top_k(spark, df, F.pmod("vec_id", F.lit(20)) == 0).collect()}
    singles = [(i, [np.float32(x) if x is not None else None for x in v] if v is not None else None) for i, v in rows]
    assert got == brute_top(singles, 10, 20)


def test_top_k_deals_each_vector_to_one_band(spark):
    """Thousands of vectors, the real block sizes: the cuts between bands are sampled, the answer must not depend on them."""
    rng = np.random.default_rng(5)
    x = rng.normal(size=(20_000, 16)).astype(np.float32)
    x /= np.linalg.norm(x, axis=1, keepdims=True)
    df = spark.createDataFrame(list(enumerate(x.tolist())), "vec_id long, embedding array<float>").repartition(4)
    whole = np.floor(x.astype(np.float64) * 1024)
    want = {}
    for q in range(0, len(x), 100):
        scores = whole @ whole[q]
        scores[q] = -np.inf
        for rank, i in enumerate(np.lexsort((np.arange(len(x)), -scores))[:10].tolist()):
            want[q, rank + 1] = (i, int(scores[i]))
    for _ in range(2):
        got = [((r["query_id"], r["rank"]), (r["vec_id"], r["score"])) for r in top_k.top_k(spark, df, F.pmod("vec_id", F.lit(100)) == 0).collect()]
        assert len(got) == len(want) and dict(got) == want


def test_top_k_of_few_and_none(spark):
    few = spark.createDataFrame([(0, [1.0, 2.0]), (1, [2.0, 1.0])], "vec_id long, embedding array<float>")
    assert [tuple(r) for r in top_k.top_k(spark, few, F.col("vec_id") == 0).collect()] == [(0, 1, 1, 4 * 1024 * 1024)]
    assert top_k.top_k(spark, few.limit(0), F.col("vec_id") == 0).count() == 0
    huge = np.array([[2.0**40, 1.0]])
    assert top_k._exact_scores(huge, huge)[0][0] == 2**80 + 1


# packing


def brute_pack(items, capacity):
    bins, out = [], {}
    todo = sorted(((-n, d, s, c) for d, n, s, c in items if n and n > 0), key=lambda x: (x[0], x[1]))
    for n, d, s, c in todo:
        fits = [(b["left"], k) for k, b in enumerate(bins) if b["left"] >= -n and (s is None or s not in b["s"]) and (c is None or c not in b["c"])]
        if fits:
            k = min(fits)[1]
        else:
            k = len(bins)
            bins.append({"left": capacity, "s": set(), "c": set()})
        out[d] = (k, capacity - bins[k]["left"])
        bins[k]["left"] += n
        bins[k]["s"] |= {s} - {None}
        bins[k]["c"] |= {c} - {None}
    return out


def test_packing_matches_brute_force():
    rnd = random.Random(6)
    items = [(d, rnd.randrange(0, 101), rnd.choice([None, "s0", "s0", "s1", "s2", "s3"]), rnd.choice([None, 1, 2, 3] + list(range(10, 400)))) for d in range(400)]
    got = {items[k][0]: (number, start) for k, _, _, number, start in packing.pack_items(items, 100) if number is not None}
    assert got == brute_pack(items, 100)


def test_shards_match_brute_force(spark):
    """The query's way, with several shards: each shard is packed like the plain version packs it alone."""
    rnd = random.Random(16)
    items = [(d, rnd.randrange(1, 101), rnd.choice([None, "s0", "s0", "s1", "s2", "s3"]), rnd.choice([None, 1, 2, 3] + list(range(10, 400)))) for d in range(600)]
    df = spark.createDataFrame(items, "doc_id long, length long, source string, cluster long")
    shards = spark.createDataFrame([(i[0], *i[1:]) for i in items], "doc_id long, length long, source string, cluster long").select("doc_id", F.pmod(F.xxhash64("doc_id", "cluster", "length"), F.lit(6)).alias("shard"))
    shard = {r["doc_id"]: r["shard"] for r in shards.collect()}
    got = {r["doc_id"]: (r["bin"], r["start"]) for r in packing.pack(df, 600, 100, 100).collect()}
    want = {}
    for s in set(shard.values()):
        want |= {d: ((s << 32) + b, at) for d, (b, at) in brute_pack([i for i in items if shard[i[0]] == s], 100).items()}
    assert len(set(shard.values())) == 6 and got == want


def test_packing_edge_cases(spark):
    rows = [(1, "w " * 5000, "en", "s"), (2, None, "en", None), (3, "", "en", "s"), (4, "a b", "en", "t"), (4, "a b", "en", "u"), (None, "c d e", None, None), (5, "x y", "en", "s")]
    got = packing.pack_documents(frame(spark, rows)).collect()
    assert sum(r["length"] for r in got if r["doc_id"] == 1) == 5000 and [r["bin"] for r in got if r["doc_id"] in (2, 3)] == [None, None]
    assert len({r["bin"] for r in got if r["doc_id"] == 4}) == 2
    for b in {r["bin"] for r in got if r["bin"] is not None}:
        own = sorted((r["start"], r["length"]) for r in got if r["bin"] == b)
        assert all(a + n == c for (a, n), (c, _) in zip(own, own[1:])) and own[0][0] == 0 and sum(n for _, n in own) <= packing.CAPACITY
    assert packing.pack_documents(frame(spark, [])).count() == 0


# chat formatting


def test_prompt_is_the_common_prefix(spark):
    rows = [(1, 0, "user", "hi", 1), (1, 1, "assistant", "yes", 1), (1, 2, "user", "more", 1), (1, 3, "assistant", "a long answer", 1), (2, 0, "user", "hi", 1), (2, 1, "assistant", "yes", 1), (2, 2, "user", "less", 1), (2, 3, "assistant", "ok", 1)]
    rows += [(2, 3, "assistant", "ok", 1), (3, 0, None, None, 1), (None, 0, "user", "hi", 1), (4, 0, "user", "only", 1)]
    df = spark.createDataFrame(rows, "conv_id long, turn int, role string, text string, turns int")
    got = {(r["made_by"], r["chosen_id"]): r for r in chat_format.formatted(df).collect()}
    assert set(got) == {("sibling", 1), ("swap", 1), ("swap", 2)}
    r = got["sibling", 1]
    assert (r["rejected_id"], r["n_common"]) == (2, 2)
    assert r["prompt"] == "<|user|>\nhi<|end|>\n<|assistant|>\nyes<|end|>\n"
    assert [r["chosen"][s["start"] : s["end"]] for s in r["chosen_spans"]] == ["a long answer<|end|>"]
    assert got["swap", 1]["rejected"] == "<|assistant|>\nok<|end|>\n" and got["swap", 2]["n_common"] == 3
    assert chat_format.formatted(df.limit(0)).count() == 0
