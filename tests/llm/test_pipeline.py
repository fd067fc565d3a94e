"""The pipeline against a brute-force version of its stages, on a small documents table."""

import random
import sys
from collections import Counter
from pathlib import Path

import sentencepiece

sys.path.insert(0, str(Path(__file__).resolve().parents[2]))
import corpus_pipeline  # noqa: E402
from cellsieve.llm import op01_secrets, op02_mixing, op08_pieces  # noqa: E402

from .test_operators import SCHEMA, bag, brute_bad, brute_mix, weighted_jaccard, words  # noqa: E402


def test_pipeline_matches_brute_force(spark, tmp_path):
    rng = random.Random(8)
    data = []
    for i in range(120):
        t = words(rng, rng.randint(30, 200))
        if i % 7 == 0:
            t += ' token = "2abc3ff2ca8fb1e4c565a0eb63815530a948bdde" end'
        data.append((i, t, "en", rng.choice(["src0", "b", None]), len(t)))
    data += [(200 + i, data[i][1] + " one more", "en", "b", len(data[i][1]) + 9) for i in range(15)]
    data += [data[3], (300, None, "en", "b", None), (301, "", "en", "b", 0), (302, "x | y | z", "en", "b", 9), (None, words(rng, 50), "en", "src0", 1)]
    spark.createDataFrame(data, SCHEMA).write.parquet(str(tmp_path / "documents.parquet"))
    kept = [r for r in data if not brute_bad(r[1])]
    # groups are far above or below the threshold here
    stay, bags = [], []
    for r in sorted(kept, key=lambda r: (r[0] is None, r[0] or 0)):
        b = bag(r[1])
        if all(weighted_jaccard(b, c) < 0.5 for c in bags):
            stay.append(r)
        bags.append(b)
    redacted = [(r[0], op01_secrets.redacted(r[1]), r[2], r[3], r[4] if op01_secrets.redacted(r[1]) == r[1] else len(op01_secrets.redacted(r[1]))) for r in stay]
    assert any("[assigned_value]" in r[1] for r in redacted)
    mixed = brute_mix(redacted, op02_mixing.WEIGHTS, op02_mixing.SEED)
    ref = sentencepiece.SentencePieceProcessor(model_file=op08_pieces.MODEL)
    want = Counter()
    for r, n in mixed.items():
        want[(r[0], tuple(ref.encode(r[1])), True)] += n
    got = Counter((r["doc_id"], tuple(r["ids"]), r["exact"]) for r in corpus_pipeline.run(spark, str(tmp_path)).collect())
    assert got == want


def test_stages_on_an_empty_table(spark, tmp_path):
    docs = spark.createDataFrame([], SCHEMA)
    for _, stage in corpus_pipeline.STAGES[:-1]:
        docs = stage(spark, docs, str(tmp_path))
        assert docs.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert corpus_pipeline.STAGES[-1][1](spark, docs, str(tmp_path)).count() == 0
