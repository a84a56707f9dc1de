"""The pipeline against a plain Python version of its stages."""

import hashlib
import re
from collections import Counter, defaultdict

import pytest
import public_tokenizers
from tokenizers import Tokenizer

import corpus_pipeline
from subvote.llm import quality_rules
from subvote.llm._store import documents
from tests.llm.test_operators import WORD, brute_components


def plain_mix(rows):
    """(doc_id, text) of the mixture for rows (doc_id, text, source)."""
    size = Counter()
    for _, t, s in rows:
        size[s] += len(WORD.findall(t or ""))
    names = sorted(s for s in size if s is not None) + ([None] if None in size else [])
    weight = {s: (3.0, 1.0, 2.0)[i % 3] for i, s in enumerate(names)}
    left, target, free = 1.5 * sum(size.values()), {}, set(names)
    while free:
        level = left / sum(weight[s] for s in free)
        full = {s for s in free if weight[s] * level > 2 * size[s]}
        if not full:
            target |= {s: weight[s] * level for s in free}
            break
        for s in full:
            target[s] = 2.0 * size[s]
            left -= target[s]
        free -= full
    out, by_source = [], defaultdict(list)
    for d, t, s in rows:
        by_source[s].append((hashlib.md5(str(d).encode()).hexdigest(), d, t))
    for s, found in by_source.items():
        goal = int(target[s])
        epochs, rest = divmod(goal, size[s]) if size[s] else (0, 0)
        for _, d, t in sorted(found):
            words = WORD.findall(t or "")
            out += [(d, t)] * (epochs if words else 0)
            take = min(len(words), max(rest, 0))
            rest -= len(words)
            if take:
                out.append((d, t if take == len(words) else " ".join(words[:take])))
    return out


def test_stages(spark, sf):
    assert [n for n, _ in corpus_pipeline.STAGES] == ["quality_rules", "exact_dedup", "ngram_jaccard_join", "mixing", "packing"]
    df = documents(spark, sf)
    field = quality_rules.fit(df, spark.read.parquet(f"{sf}/labels.parquet"))
    good = {r["doc_id"] for r in quality_rules.judge(df, field).filter("kept").collect()}
    rows = [(r["doc_id"], r["text"], r["source"]) for r in df.collect() if r["doc_id"] in good]
    best = {}
    for d, t, s in rows:
        key = re.sub(r"[\x20\x09-\x0D]", "", t or "")
        rank = (-len(t or ""), d)
        if key not in best or rank < best[key][0]:
            best[key] = (rank, (d, t, s))
    rows = [r for _, r in best.values()]
    names = brute_components([(d, t or "") for d, t, _ in rows], 5, 80)
    rows = [r for r in rows if names[r[0]][1] == r[0]]
    mixed = plain_mix(rows)
    library = Tokenizer.from_file(public_tokenizers.path("word_bpe_49k.json"))
    want = Counter((d, len(library.encode(t or "", add_special_tokens=False).ids) + 1) for d, t in mixed)
    out = corpus_pipeline.run(spark, sf).collect()
    got = Counter((r["doc_id"], r["doc_tokens"]) for r in out if r["start"] == 0)
    assert got == want


@pytest.mark.parametrize("stage", [0, 1, 2, 3])
def test_columns_stay(spark, sf, stage):
    df = documents(spark, sf).limit(40)
    assert corpus_pipeline.STAGES[stage][1](spark, df, sf).columns == df.columns


def test_empty_table_runs_through(spark, sf, tmp_path):
    docs = documents(spark, sf).limit(0)
    for _, stage in corpus_pipeline.STAGES:
        docs = stage(spark, docs, sf)
        docs.write.parquet(str(tmp_path / stage.__name__))
        docs = spark.read.parquet(str(tmp_path / stage.__name__))
    assert docs.count() == 0


def test_stages_on_odd_rows(spark, sf):
    """Nulls, repeats and columns named like the operators' own go through every stage."""
    from pyspark.sql import functions as F

    from tests.llm.test_operators import ODD, SCHEMA

    names = ("keep_id", "group_size", "kept", "size", "taken", "component_id", "start", "length", "sequence_id", "sid", "token")
    df = spark.createDataFrame(ODD, SCHEMA).withColumns({n: F.lit(None).cast("string") for n in names})
    rows = df.count()
    for _, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, df, sf)
        assert out.columns == df.columns and out.count() <= 2 * rows
    assert corpus_pipeline.STAGES[-1][1](spark, df, sf).count() > 0
