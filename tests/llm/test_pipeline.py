"""The pipeline's rows against its stages done by hand."""

import re
import zlib

import numpy as np
import public_tokenizers
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from deltafold.llm import quality_rules, secret_crf


def test_pipeline_equals_its_stages_by_hand(spark, tmp_path):
    rng = np.random.default_rng(3)
    words = [f"word{i}" for i in range(400)]
    texts = [" ".join(rng.choice(words, 60)) + "." for _ in range(60)]
    texts += [texts[0], texts[1].replace(" ", "  "), texts[2].replace(texts[2].split()[30], "changed", 1), texts[3] + ' token = "24be64439e3e49cf46b2d7c90f3602a3d0b907ff"', "", None]
    texts += ["*** ### $$$ ||| !!! " * 12 + str(i) for i in range(40)]
    rows = [(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)]
    spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").write.parquet(f"{tmp_path}/documents.parquet")
    spark.createDataFrame([(i, int(i < 66), 0) for i in range(len(texts))], "doc_id long, quality int, toxic int").write.parquet(f"{tmp_path}/labels.parquet")

    docs = spark.read.parquet(f"{tmp_path}/documents.parquet")
    model = quality_rules.train_for(spark, docs, str(tmp_path))
    kept = {r.doc_id: r.text for r in quality_rules.scored(docs, model, [F.col("doc_id"), F.col("text")]).where("score >= 0.5").collect()}
    assert set(range(60)) <= set(kept) and not set(range(66, 106)) & set(kept)
    first = {}
    for d in sorted(kept):
        first.setdefault(re.sub(r"[\x20\x09-\x0D]+", " ", kept[d] or ""), d)
    kept = {d: kept[d] for d in first.values()}

    def shingles(t):
        w = re.findall(r"[^\x20\x09-\x0D]+", (t or "").lower())
        return {tuple(w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {tuple(w)} if w else set()

    sets, root = {d: shingles(t) for d, t in kept.items()}, {d: d for d in kept}
    for a in sorted(sets):
        for b in sorted(sets):
            both = len(sets[a] & sets[b])
            if a < b and both and 100 * both >= 75 * len(sets[a] | sets[b]):
                root = {x: min(root[a], root[b]) if r in (root[a], root[b]) else r for x, r in root.items()}
    kept = {d: t for d, t in kept.items() if root[d] == d}
    lib = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = {}
    for d, t in kept.items():
        ids = lib.encode(secret_crf.redact(t or "", secret_crf.base_spans(t or "")), add_special_tokens=False).ids + [0]
        want[d] = zlib.crc32(np.array(ids, "<u4").tobytes())
    got = corpus_pipeline.run(spark, str(tmp_path)).collect()
    assert {r.doc_id: r.ids_crc32 for r in got} == want and len(got) == len(want)
    assert 4 <= len(corpus_pipeline.STAGES) <= 5
