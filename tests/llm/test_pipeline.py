"""The pipeline against a plain rendering of its stages on a small fixture."""

import sys
from pathlib import Path

import corpus_pipeline
import numpy as np
from attention_engine.llm import nearcopies, quality

sys.path.insert(0, str(Path(__file__).parent))
from test_operators import WORD, fold, prose  # noqa: E402


def test_stages(spark, tmp_path):
    base = [prose(i, 70) for i in range(10)]
    leak = " ".join(base[9].split()[5:45])
    texts = [*base[:8], base[0], "one two", base[1] + "\n" + prose(40, 40), prose(41, 30) + " " + leak, base[2] + "\n" + base[3], None]
    docs = spark.createDataFrame([(i, t, "en", f"s{i}", len(t or "")) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    docs.write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(1, leak)], "item_id long, text string").write.parquet(f"{tmp_path}/benchmark.parquet")
    kept = {r.doc_id for r in quality.quality(docs).where("kept").collect()}
    assert kept == set(range(13)) - {9}
    left, seen = {}, []
    for i in sorted(kept):
        lines = []
        for line in texts[i].split("\n"):
            w = frozenset(fold(line).split())
            if not (w and any(5 * len(w & v) >= 4 * len(w | v) for v in seen)):
                lines.append(line)
            seen.append(w)
        left[i] = "\n".join(lines)
    bare = [i for i in left if not WORD.findall(left[i])]
    want = {i: len(WORD.findall(t)) for i, t in left.items() if i not in bare[1:] and i != 11}
    got = {}
    for r in corpus_pipeline.run(spark, str(tmp_path)).collect():
        got[r.doc_id] = got.get(r.doc_id, 0) + r.n_words
    assert got == want
    out = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, out, str(tmp_path))
        assert out.columns == docs.columns


def test_near_copies_of_080_to_095_go(spark):
    rng = np.random.default_rng(5)
    texts = [" ".join(f"w{x}" for x in rng.integers(0, 5000, n)) for n in (3, 40, 90, 200, 400, 900)] + ["", "  ", "w1 w2"]
    for base in texts[1:6]:
        for share in (0.004, 0.01, 0.02, 0.03, 0.04):
            words = base.split()
            for k in rng.choice(len(words), max(1, int(share * len(words))), replace=False):
                words[k] = f"new{rng.integers(0, 10**6)}"
            texts.append(" ".join(words).upper())
    sets = [frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if (w := t.lower().split()) else frozenset() for t in texts]
    like = lambda a, b: not (a or b) or 5 * len(a & b) >= 4 * len(a | b)
    root = list(range(len(texts)))
    for _ in texts:
        root = [min(root[j] for j in range(len(texts)) if like(sets[i], sets[j])) for i in range(len(texts))]
    assert sum(0.8 <= len(a & b) / len(a | b) < 0.95 for i, a in enumerate(sets) for b in sets[:i] if a and b) >= 12
    docs = spark.createDataFrame([(i, t, "en", "s", len(t)) for i, t in enumerate(texts)], "doc_id long, text string, lang string, source string, n_chars long")
    left = corpus_pipeline.keep_one_of_near_copies(spark, docs.repartition(3), "")
    assert {r.doc_id for r in left.collect()} == set(root)
    assert nearcopies.near_copies(docs.limit(0)).count() == 0


def test_near_copies_against_brute_force(spark):
    """Families around the limit, passages that many texts share, copies, and texts of a few words."""
    rng = np.random.default_rng(6)
    texts = ["", "one", "ONE", "one two three", "Three two one"]
    passage = [f"p{k}" for k in range(40)]
    for _ in range(40):
        base = rng.integers(0, 9000, 80)
        for p in (0, 0.01, 0.02, 0.03, 0.05, 0.08):
            texts.append(" ".join(f"w{x}" for x in np.where(rng.random(80) < p, rng.integers(0, 9000, 80), base)))
    texts += [" ".join([*passage, *(f"q{x}" for x in rng.integers(0, 9000, 12))]) for _ in range(60)]
    texts += texts[5:20]
    sets = [frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if (w := t.lower().split()) else frozenset() for t in texts]
    near = [[j for j, b in enumerate(sets) if a == b or 5 * len(a & b) >= 4 * len(a | b)] for a in sets]
    want = list(range(len(texts)))
    while (nxt := [min(want[j] for j in row) for row in near]) != want:
        want = nxt
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(5)
    got = {r.doc_id: r.component_id for r in nearcopies.near_copies(docs).collect()}
    assert [got[i] for i in range(len(texts))] == want and 60 < len(set(want)) < len(texts) - 60
