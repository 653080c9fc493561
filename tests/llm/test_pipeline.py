import corpus_pipeline
from tests.llm.test_operators import brute_lines, brute_near, edit_within
from blockgraph.llm import decontamination, packing


def test_stages_match_brute_force(spark, sf):
    """Each stage on its own input against a plain version; the last one by its constraints."""
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    rows = lambda df: {r["doc_id"]: r["text"] for r in df.select("doc_id", "text").collect()}
    steps = dict(corpus_pipeline.STAGES)

    named = corpus_pipeline.materialise(steps["language_id"](spark, docs, sf), "t1")
    assert named.columns == docs.columns and set(rows(docs)) - set(rows(named)) == {d for d, t in rows(docs).items() if not any(c.isalpha() for c in t or "")}

    lines = corpus_pipeline.materialise(steps["line_dedup"](spark, named, sf), "t2")
    want = {d: kept for d, (_, gone, kept) in brute_lines([(d, t) for d, t in rows(named).items()]).items() if not gone or kept.replace("\n", "").strip(" ")}
    assert lines.columns == docs.columns and rows(lines) == want

    near = corpus_pipeline.materialise(steps["near_dedup"](spark, lines, sf), "t3")
    groups = brute_near([(d, t) for d, t in rows(lines).items()])
    assert near.columns == docs.columns and rows(near) == {d: t for d, t in rows(lines).items() if groups[d][1] == d}

    clean = corpus_pipeline.materialise(steps["decontamination"](spark, near, sf), "t4")
    items = [decontamination.symbols(r["text"].encode()).tolist() for r in spark.read.parquet(f"{sf}/benchmark.parquet").collect()]
    holds = lambda t: any(edit_within(i, s, 99) <= decontamination.allowed_edits(len(i), 0.2) for i in items) if (s := decontamination.symbols(t.encode()).tolist()) else False
    assert clean.columns == docs.columns and set(rows(clean)) == {d for d, t in rows(near).items() if not holds(t)}

    placed = steps["packing"](spark, clean, sf).collect()
    lengths = {d: len(t.encode().split()) for d, t in rows(clean).items()}
    assert {d: sum(r["length"] for r in placed if r["doc_id"] == d) for d in lengths} == lengths
    fill = {}
    for r in placed:
        fill[r["bin"]] = fill.get(r["bin"], 0) + r["length"]
    assert max(v for b, v in fill.items() if b is not None) <= packing.CAPACITY


def test_run_gives_the_last_stage(spark, sf):
    assert corpus_pipeline.run(spark, sf).columns == ["doc_id", "piece", "length", "bin", "start"]
