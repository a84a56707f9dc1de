"""Brute-force versions, round trips and the defined edge cases of the text operators."""

import hashlib
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from subvote.llm import chat_format, exact_dedup, language_id, mixing, ngram_join, packing, quality_rules, queries, substring_dedup, token_counts, token_files
from subvote.llm._store import documents
from subvote.llm._text import Words, text_slices
from subvote.llm.components import components

WORD = re.compile(r"[^\x20\x09-\x0D]+")
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, hits string, _rank int"
ODD = [
    (1, None, None, None, None, "x", 1), (2, "", "en", None, 0, "x", 1), (3, " \t\n", "en", "b", 3, "x", 1), (4, "one", "en", "a", 3, "x", 1),
    (5, "one", "en", "a", 3, "x", 1), (6, "o n\te", "de", "a", 3, "x", 1), (None, "null id text here with words", "en", "c", 5, None, None),
    (7, "a b c d e f g h i j " * 30, "en", "a", 600, "x", 1), (8, "a b c d e f g h i j " * 30, "en", "a", 600, "x", 1),
    (9, "word " * 20000, "en", "b", 100000, "x", 1), (10, "été ÜBER straße \u00a0 \x1c \u4e2d\u6587 <|endoftext|> </s>[INST] \\ ", "fr", "a", 1, "x", 1),
    (4, "one", "en", "a", 3, "x", 1),
]


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, SCHEMA)


@pytest.fixture(scope="module")
def docs(spark, sf):
    return [(r["doc_id"], r["text"] or "") for r in documents(spark, sf).collect()]


def brute_components(docs, k, percent):
    sets = {}
    for d, t in docs:
        w = t.encode().lower().split()
        sets[d] = {tuple(w[i : i + k]) for i in range(len(w) - k + 1)} if len(w) >= k else ({tuple(w)} if w else set())
    parent = {d: d for d in sets}

    def top(x):
        while parent[x] != x:
            x = parent[x]
        return x

    ids = sorted(sets)
    for i, a in enumerate(ids):
        for b in ids[:i]:
            n = len(sets[a] & sets[b])
            if n and 100 * n >= percent * (len(sets[a]) + len(sets[b]) - n):
                x, y = top(a), top(b)
                parent[max(x, y)] = min(x, y)
    return {d: (len(s), top(d)) for d, s in sets.items()}


@pytest.mark.parametrize("k, percent", [(3, 90), (5, 80)])
def test_join_is_exact(spark, sf, docs, k, percent):
    got = {r[0]: (r[1], r[2]) for r in ngram_join.join(documents(spark, sf), k, percent).collect()}
    assert got == brute_components(docs, k, percent)


def test_join_of_a_large_family(spark):
    """Near copies that link through hubs only, exact copies, and short texts."""
    rng = np.random.default_rng(5)
    base = [f"w{i}" for i in rng.integers(0, 400, 120)]
    rows = [(0, " ".join(base))]
    for d in range(1, 160):
        w = list(base)
        for p in rng.choice(120, rng.integers(0, 3), replace=False):
            w[p] = f"x{d}.{p}"
        rows.append((d, " ".join(w)))
    rows += [(200 + d, "tiny text") for d in range(4)] + [(300, None), (301, ""), (302, "Tiny TEXT")]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for k, percent in ((3, 90), (3, 95), (5, 80)):
        got = {r[0]: (r[1], r[2]) for r in ngram_join.join(df, k, percent).collect()}
        assert got == brute_components([(d, t or "") for d, t in rows], k, percent)


def test_join_opens_groups(spark):
    """Chains of near copies across sizes: links between groups are found."""
    rng = np.random.default_rng(9)
    rows = []
    for family in range(6):
        w = [f"f{family}.{i}" for i in range(60)]
        for step in range(12):
            rows.append((len(rows), " ".join(w)))
            w = [*w, f"f{family}+{step}.{rng.integers(9)}", *([f"f{family}-{step}"] if step % 2 else [])]
            if step % 3 == 0:
                w[int(rng.integers(len(w)))] = f"edit{len(rows)}"
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r[0]: (r[1], r[2]) for r in ngram_join.join(df, 3, 90).collect()}
    assert got == brute_components(rows, 3, 90)


@pytest.mark.parametrize("k, percent, words, own", [(3, 90, 67, (3, 4, 5)), (5, 80, 25, (2, 3, 4))])
def test_join_of_three_sizes(spark, k, percent, words, own):
    """One passage with 3 lengths of own words: the number required is least inside the range of sizes."""
    passage = [f"p{i}" for i in range(words)]
    rows = [(d, " ".join([*passage, *(f"x{d}.{i}" for i in range(n))])) for d, n in enumerate(own)]
    got = {r[0]: (r[1], r[2]) for r in ngram_join.join(spark.createDataFrame(rows, "doc_id long, text string"), k, percent).collect()}
    assert got == brute_components(rows, k, percent)
    assert got[0][1] == got[1][1]


def test_blocks_find_all_components():
    import pyarrow as pa

    rng = np.random.default_rng(1)
    sets = [np.unique(rng.integers(0, 60, 30).astype(np.uint64)) for _ in range(40)]
    table = lambda idx: pa.table({"sid": pa.array([bytes([i]) for i in idx]), "root": pa.array([bytes([i]) for i in idx]), "tokens": pa.array([sets[i].tobytes() for i in idx], pa.binary())})
    links = ngram_join.block_links(table(range(40)), table(range(40)), 40)
    parent = list(range(40))
    find = lambda x: x if parent[x] == x else find(parent[x])
    for i in range(40):
        for j in range(i):
            n = len(np.intersect1d(sets[i], sets[j]))
            if 100 * n >= 40 * (len(sets[i]) + len(sets[j]) - n):
                parent[find(i)] = find(j)
    want = {frozenset(x for x in range(40) if find(x) == find(i)) for i in range(40)}
    parent = list(range(40))
    for a, b in links:
        parent[find(a[0])] = find(b[0])
    assert {frozenset(x for x in range(40) if find(x) == find(i)) for i in range(40)} == want


def test_components(spark):
    edges = [(i, i + 1) for i in range(30)] + [(100, 101), (102, 101), (7, 7)]
    got = dict(components(spark.createDataFrame(edges, "a long, b long")).collect())
    assert got == {**{i: 0 for i in range(1, 31)}, 101: 100, 102: 100}
    assert components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_exact_dedup(spark, odd):
    got = {(r["doc_id"], r["text_sha256"]): r for r in exact_dedup.groups(odd).collect()}
    assert {r["keep_id"] for r in got.values() if r["doc_id"] in (4, 5, 6)} == {6}  # most code points
    one = next(r for r in got.values() if r["doc_id"] == 5)
    assert one["group_size"] == 4 and not one["kept"] and one["text_sha256"] == hashlib.sha256(b"one").hexdigest()
    assert {r["group_size"] for r in got.values() if r["doc_id"] in (1, 2, 3)} == {3}
    assert {r["keep_id"] for r in got.values() if r["doc_id"] in (1, 2, 3)} == {3}
    kept = exact_dedup.kept_rows(odd)
    assert kept.columns == odd.columns and sorted(r["doc_id"] or 0 for r in kept.collect()) == [0, 3, 6, 7, 9, 10]


def test_exact_dedup_survives_collisions(spark, odd):
    """With a hash that is the same for all, the bytes decide."""
    want = sorted(map(str, exact_dedup.groups(odd).collect()))
    got = exact_dedup.groups(odd, hash_of=lambda c: F.when(c.isNotNull(), F.lit("00")))
    assert sorted(map(str, got.select(*exact_dedup.groups(odd).columns).collect())) == want


def test_repeated_rows_keep_one(spark):
    df = spark.createDataFrame([(1, "a b")] * 5 + [(2, "ab"), (3, "c"), (1, "ab"), (3, "d")], "doc_id long, text string")
    assert sorted(exact_dedup.kept_rows(df).collect()) == [(1, "a b"), (3, "c"), (3, "d")]


def test_quality_base_columns(spark, sf, docs):
    df = documents(spark, sf)
    field = quality_rules.fit(df, spark.read.parquet(f"{sf}/labels.parquet"))
    got = {r["doc_id"]: r for r in quality_rules.judge(df, field).collect()}
    for d, t in docs:
        words, lines = WORD.findall(t), t.split("\n")
        seen, dup = set(), 0
        for line in lines:
            if WORD.search(line):
                dup += line in seen
                seen.add(line)
        windows = [tuple(words[i : i + 3]) for i in range(len(words) - 2)]
        times = Counter(windows)
        cover = {i + j for i, w in enumerate(windows) if times[w] > 1 for j in range(3)}
        r = got[d]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(words), sum(map(len, words)), len(re.findall(r"[#*$%&|<>]", t)), dup, len(cover))
        assert r["base_failed"] == (len(words) < 50 or 100 * len(cover) > 50 * len(words)) and (r["kept"] is False or not r["base_failed"])


def test_viterbi_against_enumeration():
    rng = np.random.default_rng(2)
    doc = np.array([0, 0, 0, 0, 1, 3, 3])
    lines = quality_rules.Lines(doc, rng.standard_normal((7, 3)), np.ones(7), {})
    field = quality_rules.Field(rng.standard_normal(3), rng.standard_normal((2, 2)))
    got = quality_rules.decode(field, lines, 4)
    score = lines.features @ field.weights
    for d in (0, 1, 3):
        at = np.flatnonzero(doc == d)
        best = max(
            (sum(score[i] * y for i, y in zip(at, ys, strict=True)) + sum(field.transitions[a, b] for a, b in zip(ys, ys[1:], strict=False)), ys)
            for ys in np.ndindex(*(2,) * len(at))
        )
        assert tuple(got[at]) == best[1]


def test_training_separates(spark):
    doc = np.repeat(np.arange(40), 3)
    quality = np.arange(40) % 2
    x = np.stack([np.ones(120), np.repeat(quality, 3) * 2.0 - 1 + np.random.default_rng(0).normal(0, 0.3, 120)], axis=1)
    field = quality_rules.train(quality_rules.Lines(doc, x, np.ones(120), {}), np.repeat(quality, 3), 40)
    label = quality_rules.decode(field, quality_rules.Lines(doc, x, np.ones(120), {}), 40)
    assert (label == np.repeat(quality, 3)).mean() > 0.97


def test_quality_edge_cases(spark, odd, sf):
    out = quality_rules.judge(odd, quality_rules.PRIOR)
    assert out.count() == len(ODD) and {r["n_words"] for r in out.filter("doc_id in (1, 2, 3)").collect()} == {0}
    assert quality_rules.kept_rows(odd, quality_rules.PRIOR).columns == odd.columns
    empty = spark.createDataFrame([], "doc_id long, quality int")
    assert quality_rules.fit(odd, empty) is quality_rules.PRIOR


def test_chat_escape_round_trip(spark):
    texts = ["", "\\", "[INST]", "[\\INST]", "[\\\\INST]", "</s></s>", "<</s>s>", "<|image:1|>", "[/INST] a\\", "\\</s>", "<s><s", "é\n"]
    df = spark.createDataFrame([(t,) for t in texts], "t string").withColumn("e", chat_format.escape(F.col("t")))
    for t, e, u in df.select("t", "e", chat_format.unescape(F.col("e"))).collect():
        assert t == u and not any(c in e for c in chat_format.CONTROLS)


def test_chat_parts_and_loss(spark):
    parts = "array<struct<kind:string,text:string,ref:string,width:double,height:double>>"
    rows = [
        (1, 0, "user", [("text", "look </s> ", None, None, None), ("image", None, "s3://i.png", 280.0, 140.0), ("audio", None, "a.wav", 2.0, None)]),
        (1, 1, "assistant", [("text", "ok [INST]", None, None, None)]), (1, 2, None, [("document", None, "d.pdf", 3.0, None), ("text", None, None, None, None)]),
        (1, 3, "assistant", None), (None, 0, "user", []),
    ]
    out = {r["conv_id"]: r for r in chat_format.format_chats(spark.createDataFrame(rows, f"conv_id long, turn int, role string, parts {parts}")).withColumn("turns", chat_format.read_turns(F.col("formatted"))).withColumn("loss", chat_format.read_loss(F.col("formatted"), F.col("loss_spans"))).collect()}
    r = out[1]
    assert [(a["ordinal"], a["kind"], a["ref"], a["tokens"]) for a in r["attachments"]] == [(1, "image", "s3://i.png", 200), (2, "audio", "a.wav", 50), (3, "document", "d.pdf", 2100)]
    assert r["expanded_tokens"] == 2350 and r["loss"] == "ok [INST]"
    assert "<|image:1|><|audio:2|></s>" in r["formatted"] and "<|document:3|></s>" in r["formatted"]
    assert [t["role"] for t in r["turns"]] == ["user", "assistant", "", "assistant"] and r["turns"][1]["text"] == "ok [INST]"
    assert out[None]["n_turns"] == 1 and out[None]["loss"] == ""


def test_chat_is_native(spark, sf):
    plan = queries.op4_chat_format(spark, sf)._jdf.queryExecution().executedPlan().toString()
    assert "Python" not in plan and "Arrow" not in plan


def brute_ids(texts, name, end):
    library = Tokenizer.from_file(public_tokenizers.path(name))
    return [np.array([*e.ids, end], "<u4") for e in library.encode_batch([t or "" for t in texts], add_special_tokens=False)]


def test_packing(spark, odd, sf):
    for df in (odd, documents(spark, sf)):
        texts = [(r["doc_id"], r["text"]) for r in df.select("doc_id", "text").collect()]
        want = defaultdict(list)
        for (d, _), ids in zip(texts, brute_ids([t for _, t in texts], "word_bpe_49k.json", 2), strict=True):
            want[d].append(ids)
        out = packing.pack(df, public_tokenizers.path("word_bpe_49k.json")).collect()
        for r in out:
            assert any(zlib.crc32(i[r["start"] : r["start"] + r["length"]].tobytes()) == r["ids_crc32"] and len(i) == r["doc_tokens"] for i in want[r["doc_id"]])
        assert sum(r["length"] for r in out) == sum(len(i) for v in want.values() for i in v)
        by_sequence = defaultdict(list)
        for r in out:
            by_sequence[r["sequence_id"]].append((r["offset"], r["length"]))
        for spans in by_sequence.values():
            at = 0
            for offset, length in sorted(spans):
                assert offset == at
                at += length
            assert at <= 4096
        assert sorted(by_sequence) == list(range(len(by_sequence)))
    assert packing.pack(odd.limit(0), public_tokenizers.path("word_bpe_49k.json")).count() == 0


@settings(max_examples=50, deadline=None)
@given(st.dictionaries(st.integers(1, 64), st.integers(1, 200), min_size=1, max_size=30))
def test_patterns_hold_the_histogram(histogram):
    patterns = packing.plan_patterns(histogram, 64)
    held = Counter()
    for count, lengths in patterns:
        assert count > 0 and sum(lengths) <= 64
        for n in lengths:
            held[n] += count
    assert held == Counter(histogram)


def test_mixing(spark, odd):
    rows = [(i, " ".join(["w"] * (1 + i % 7)), f"s{i % 4}" if i % 9 else None) for i in range(400)] + [(900, None, "s1"), (901, "", "empty")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    out = mixing.mix(df).collect()
    size = Counter()
    for _, t, s in rows:
        size[s] += len(WORD.findall(t or ""))
    names = sorted(s for s in size if s is not None) + [None]
    weight = {s: [3, 1, 2][i % 3] for i, s in enumerate(names)}
    cap, left, target = {s: 2 * size[s] for s in names}, 1.5 * sum(size.values()), {}
    free = set(names)
    while True:
        level = left / sum(weight[s] for s in free) if free else 0
        full = {s for s in free if weight[s] * level > cap[s]}
        if not full:
            break
        for s in full:
            target[s] = cap[s]
            left -= cap[s]
        free -= full
    target |= {s: weight[s] * level for s in free}
    taken = Counter()
    for r in out:
        assert r["target"] == pytest.approx(target[r["source"]]) and r["source_size"] == size[r["source"]] and 0 <= r["taken"] <= 2 * r["size"]
        taken[r["source"]] += r["taken"]
    for s in names:
        assert taken[s] == int(target[s])
    assert sorted(map(str, mixing.mix(df.repartition(7)).collect())) == sorted(map(str, out))
    mixed = mixing.apply_mix(df)
    assert mixed.columns == df.columns
    words = Counter()
    for r in mixed.collect():
        words[r["source"]] += len(WORD.findall(r["text"]))
    assert words == +taken
    assert mixing.mix(odd).count() == len(ODD) and mixing.mix(odd.limit(0)).count() == 0


def test_language_profiles(spark, sf, odd):
    df = documents(spark, sf)
    out = queries.op7_language_id(spark, sf)
    right = out.join(df, "doc_id").filter("held_out").agg(F.avg((F.col("lang_pred") == F.col("lang")).cast("int"))).first()[0]
    assert right > 0.95 and out.filter("score < 0 or score > 1").count() == 0
    assert language_id.grams_of(np.array([ord(c) for c in "Ab 1-c"], np.uint32)).size == 3 + 5 + 3
    model = language_id.fit(odd, "true")
    got = {r["doc_id"]: r["lang_pred"] for r in language_id.predict(odd, model).collect()}
    assert got[1] == got[2] == got[3] == "und" and got[9] == "en"
    nothing = language_id.fit(odd, "false")
    assert {r["lang_pred"] for r in language_id.predict(odd, nothing).collect()} == {"und"}


def test_token_files(spark, odd, tmp_path):
    path = public_tokenizers.path("byte_bpe_50k.json")
    folder = f"file://{tmp_path}/files"
    manifest = token_files.write_token_files(odd, path, 0, folder)
    got = token_files.read_token_files(manifest, folder).orderBy("start").collect()
    ordered = sorted(((r[0], r[1]) for r in ODD), key=lambda r: (r[0] is not None, r[0] or 0, r[1] is not None, r[1] or ""))
    at = 0
    for r, (d, _), ids in zip(got, ordered, brute_ids([t for _, t in ordered], "byte_bpe_50k.json", 0), strict=True):
        assert (r["doc_id"], r["start"], r["n_tokens"], r["ids_crc32"]) == (d, at, len(ids), zlib.crc32(ids.tobytes()))
        at += len(ids)
    import zstandard

    for row in manifest.collect():
        with open(row["path"], "rb") as f:
            reader = token_files.ShardReader(f, row["bytes"])
            assert len(reader) == row["n_docs"]
            reader.ids(len(reader) - 1)
        raw = bytearray(open(row["path"], "rb").read())
        whole = zstandard.ZstdDecompressor().stream_reader(bytes(raw), read_across_frames=True).read()
        assert len(whole) > 4 * row["n_tokens"]
        raw[int(reader.starts[0]) + int(reader.packed[0]) - 1] ^= 255
        import io

        with pytest.raises(Exception):
            token_files.ShardReader(io.BytesIO(bytes(raw)), len(raw)).ids(0)
    assert token_files.write_token_files(odd.limit(0), path, 0, folder + "-none").count() == 0


def test_token_counts(spark, odd, sf):
    path = public_tokenizers.path("word_bpe_49k.json")
    for df in (odd, documents(spark, sf)):
        rows = df.select("doc_id", "text").collect()
        want = Counter((r[0], len((r[1] or "").encode()), len(i) - 1) for r, i in zip(rows, brute_ids([r[1] for r in rows], "word_bpe_49k.json", 2), strict=True))
        assert Counter((r[0], r[1], r[2]) for r in token_counts.count_tokens(df, path).collect()) == want


@settings(max_examples=60, deadline=None)
@given(st.text(alphabet="aAbé's 1.!\n\t<|endoftext>İ́", max_size=60))
def test_counts_equal_the_library(text):
    path = public_tokenizers.path("word_bpe_49k.json")
    merger = token_counts._counter(path)
    import pyarrow as pa

    total = sum(int(v.sum()) for _, _, _, v in merger.slices(pa.array([text])))
    assert total == len(Tokenizer.from_file(path).encode(text, add_special_tokens=False).ids)


def brute_repeats(docs, size):
    seen, out = set(), {}
    for d, t in sorted(docs, key=lambda r: (r[0] is not None, r[0] or 0)):
        w = t.encode().split()
        gone = [False] * len(w)
        for i in range(len(w) - size + 1):
            key = tuple(w[i : i + size])
            if key in seen:
                gone[i : i + size] = [True] * size
            seen.add(key)
        kept = [x for x, g in zip(w, gone, strict=True) if not g]
        out[d] = (len(w), sum(gone), hashlib.sha256(b" ".join(kept)).hexdigest())
    return out


@pytest.mark.parametrize("batches", [1, 2, 7])
def test_substring_dedup(spark, sf, docs, batches):
    got = {r[0]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.remove_repeats(documents(spark, sf), 20, batches).collect()}
    assert got == brute_repeats(docs, 20)


def test_substring_dedup_of_repeats_and_odd_rows(spark, odd):
    rng = np.random.default_rng(4)
    passage = " ".join(f"p{i}" for i in range(55))
    rows = [(i, " ".join([*(f"r{x}" for x in rng.integers(0, 50, 30)), passage, "ha " * int(rng.integers(0, 60))])) for i in range(30)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r[0]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.remove_repeats(df, 20, 3).collect()}
    assert got == brute_repeats(rows, 20)
    unique = odd.dropDuplicates(["doc_id"])
    got = {r[0]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.remove_repeats(unique, 20).collect()}
    assert got == brute_repeats([(r[0], r[1] or "") for r in unique.collect()], 20)
    assert substring_dedup.remove_repeats(odd, 20).count() == len(ODD)
    assert substring_dedup.remove_repeats(odd.limit(0), 20).count() == 0


def test_index_compaction(spark, sf):
    df = substring_dedup.keyed(documents(spark, sf))
    index = substring_dedup.FingerprintIndex(spark, fan_out=2)
    for i in range(4):
        index.add(df.filter(F.col("doc_id") % 4 == i), df.filter(F.col("doc_id") % 4 < i))
    assert len(index.marks) <= 2 and index.compactions == 1
    total = index.occurrences(df).groupBy("mark").count()
    held = spark.read.schema(index.marks[0].schema).parquet(*[run._subvote_path for run in index.marks])
    held = held.groupBy("mark").agg(F.sum("times").alias("count"))
    assert held.exceptAll(total).count() == 0 and total.exceptAll(held).count() == 0
    index.drop()


def test_words_are_the_contract(docs):
    import pyarrow as pa

    column = pa.array([t for _, t in docs[:60]] + [None, "", "\x0b a\x0cb\u00a0c "])
    for lo, hi, buf, offs in text_slices(column, 5000):
        words = Words(buf, offs)
        for d in range(hi - lo):
            span = slice(words.first[d], words.first[d + 1])
            got = [bytes(buf[a:b]).decode() for a, b in zip(words.starts[span], words.ends[span], strict=True)]
            assert got == WORD.findall(column[lo + d].as_py() or "")


def test_edge_rows_of_the_join(spark, odd):
    got = ngram_join.join(odd).collect()
    assert len(got) == len(ODD)
    by_id = defaultdict(set)
    for r in got:
        by_id[r["doc_id"]].add((r["n_shingles"], r["component_id"]))
    assert by_id[1] == {(0, 1)} and by_id[5] == {(1, 4)} and by_id[8] == {(10, 7)} and by_id[None] == {(2, None)}
    assert ngram_join.join(odd.limit(0)).count() == 0
