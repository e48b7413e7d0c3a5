import random
import re

import sentencepiece

import corpus_pipeline
from markerpanel.llm import decontamination, line_dedup, near_duplicates, quality_rules
from markerpanel.llm.common import NULL_ID, public_file


def corpus():
    rng = random.Random(8)
    words = [f"word{k}" for k in range(900)]
    line = lambda n: " ".join(rng.choice(words) for _ in range(n))
    shared = [line(12) for _ in range(4)]
    items = [(k, line(14)) for k in range(5)]
    rows = []
    for d in range(60):
        parts = [line(rng.choice([3, 15, 30])) for _ in range(rng.randrange(1, 5))]
        if d % 5 == 0:
            parts.append(rng.choice(shared))
        if d % 11 == 0:
            parts.append("so " + rng.choice(items)[1].upper())
        if d % 7 == 3 and rows:
            parts = [rng.choice(rows)[1] + rng.choice(["", " " + rng.choice(words)])]
        if d % 13 == 1:
            parts.append("### $$$ %% " * 20)
        rows.append((d, "\n".join(parts)))
    return [*rows, (70, None), (71, ""), (None, line(40))], items


def test_run_against_brute_force(spark, tmp_path):
    rows, items = corpus()
    spark.createDataFrame([(a, b, "en", "s", len(b or ""), 1.5) for a, b in rows], "doc_id long, text string, lang string, source string, n_chars long, kept double").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    got = {r.doc_id: (list(r.ids), r.decoded) for r in corpus_pipeline.run(spark, str(tmp_path)).collect()}

    led = {r.doc_id for r in quality_rules.apply_policy(quality_rules.ledger(spark.createDataFrame(rows, "doc_id long, text string"))).filter("kept").collect()}
    left = [(NULL_ID if d is None else d, t) for d, t in rows if d in led]
    assert 20 < len(left) < len(rows) - 3
    kept, seen = [], []
    for d, t in sorted(left):
        out = []
        for x in t.split("\n"):
            s = frozenset(re.findall(r"[^\x20\x09-\x0D]+", x.lower()))
            if len(s) < line_dedup.MIN_WORDS or not any(100 * len(s & o) >= line_dedup.LEAST * len(s | o) for o in seen):
                out.append(x)
            if len(s) >= line_dedup.MIN_WORDS:
                seen.append(s)
        kept.append((d, "\n".join(out)))
    assert kept != sorted(left)
    groups = near_duplicates.brute(kept)
    kept = [(d, t) for d, t in kept if groups[d][1] == d]
    hits = decontamination.brute(kept, items)
    clean = [(d, t) for d, t in kept if not hits[d][1]]
    assert len(clean) < len(kept)
    library = sentencepiece.SentencePieceProcessor(model_file=public_file("piece_bpe_32k.model"))
    assert got == {None if d == NULL_ID else d: ([*library.encode(t), library.eos_id()], library.decode(library.encode(t))) for d, t in clean}


def test_stages_keep_columns(spark, tmp_path):
    rows, items = corpus()
    spark.createDataFrame(items, "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    docs = spark.createDataFrame([(a, b, 1, 2, 3, 4) for a, b in [*rows, rows[0]]], "doc_id long, text string, row int, kept int, line int, n_words int")
    for name, stage in corpus_pipeline.STAGES[:-1]:
        assert stage(spark, docs, str(tmp_path)).columns == docs.columns, name
        assert stage(spark, docs.limit(0), str(tmp_path)).count() == 0, name
