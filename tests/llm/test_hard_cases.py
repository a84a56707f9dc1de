"""Constructed cases: colliding hashes, repeated ids, clashing names, split texts, the index on disk."""

import io
import json
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import public_tokenizers
import pyarrow as pa
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st
from pyspark.sql import functions as F
from tokenizers import Tokenizer

import corpus_pipeline
from subvote.llm import _text, chat_format, exact_dedup, language_id, mixing, ngram_join, packing, quality_rules, queries, substring_dedup, token_counts, token_files
from subvote.llm._store import documents
from tests.llm.test_operators import ODD, SCHEMA, WORD, brute_components, brute_ids, brute_repeats


def thue_morse(n, swap):
    """Complementary words of a and b whose polynomial hashes modulo 2**64 agree from 1,024 letters on."""
    return "".join("ab"[(bin(i).count("1") + swap) % 2] for i in range(n))


PAIRS = [thue_morse(n, swap) for n in (1024, 2048) for swap in (0, 1)]


def test_words_of_equal_polynomial_sums_differ(spark):
    df = spark.createDataFrame(list(enumerate(PAIRS)), "doc_id long, text string")
    assert {r[2] for r in ngram_join.join(df, 3, 90).collect()} == {0, 1, 2, 3}
    path = public_tokenizers.path("word_bpe_49k.json")
    ids = brute_ids(PAIRS, "word_bpe_49k.json", 2)
    got = {r["doc_id"]: (r["ids_crc32"], r["doc_tokens"]) for r in packing.pack(df, path).collect()}
    assert got == {d: (zlib.crc32(x.tobytes()), len(x)) for d, x in enumerate(ids)}
    assert {r["doc_id"]: r["n_tokens"] for r in token_counts.count_tokens(df, path).collect()} == {d: len(x) - 1 for d, x in enumerate(ids)}
    bytes_path = public_tokenizers.path("byte_bpe_50k.json")
    manifest = token_files.write_token_files(df, bytes_path, 0)
    got = [r["ids_crc32"] for r in token_files.read_token_files(manifest, manifest._subvote_folder).orderBy("doc_id").collect()]
    assert got == [zlib.crc32(x.tobytes()) for x in brute_ids(PAIRS, "byte_bpe_50k.json", 0)]
    rows = [(d, " ".join([*(f"w{i}" for i in range(12)), PAIRS[d], *(f"v{i}" for i in range(12))])) for d in range(4)]
    got = {r[0]: (r["n_words"], r["n_removed"], r["kept_sha256"]) for r in substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), 20).collect()}
    assert got == brute_repeats(rows, 20) and all(v[1] == 0 for v in got.values())


@pytest.mark.parametrize("name, spaced", [("word_bpe_49k.json", False), ("byte_bpe_50k.json", True)])
def test_memo_compares_pieces(monkeypatch, name, spaced):
    """With one hash for all pieces, every text is still encoded right."""
    from subvote.llm._tokens import Encoder, library_ids, tokenizer

    library = tokenizer(public_tokenizers.path(name))
    encoder = Encoder(lambda texts, whole: library_ids(library, texts), spaced)
    monkeypatch.setattr(_text.Spans, "hash", lambda self, salt=0: np.zeros(len(self.size), np.uint64))
    texts = ["one two three", "two", "one", "one one", "a longer word than sixteen bytes", ""]
    for _ in range(2):
        for _, _, sizes, flat in encoder.slices(pa.array(texts)):
            got = [x.tolist() for x in np.split(flat, np.cumsum(sizes)[:-1])]
            assert got == [library.encode(t, add_special_tokens=False).ids for t in texts]


@settings(max_examples=80, deadline=None)
@given(st.lists(st.text(alphabet="abé\x00ß ", max_size=40), min_size=1, max_size=12))
def test_spans_tell_bytes_apart(texts):
    raw = [t.encode() for t in texts]
    buf = np.frombuffer(b"".join(raw), np.uint8)
    ends = np.cumsum([len(r) for r in raw])
    spans = _text.Spans(buf, ends - [len(r) for r in raw], ends)
    for salt in (0, 60):
        h = spans.hash(salt)
        for i in range(len(raw)):
            for j in range(i):
                assert (h[i] == h[j]) == (raw[i] == raw[j])


@pytest.mark.parametrize("percent", [80, 90, 95])
def test_required_overlap_is_a_lower_bound(spark, percent):
    """Over all sizes and ranges of sizes below 130 the filter never asks for more than some pair needs."""
    exact = lambda a, b: -(-(a + b) * percent // (100 + percent)) - -(-max(a, b) * percent // 100) + 1
    top = 130
    need = np.array([[exact(a, b) for b in range(1, top)] for a in range(1, top)])
    run = ngram_join.Join(spark.createDataFrame([], "doc_id long, text string"), 3, percent)
    grid = spark.range(1, top).select(F.col("id").alias("n")).crossJoin(spark.range(1, top).select(F.col("id").alias("low"))).crossJoin(spark.range(1, top).select(F.col("id").alias("high")))
    grid = grid.filter(f"low <= high and low * 100 >= n * {percent} and n * 100 >= high * {percent}")
    got = grid.select("n", "low", "high", run._least_required(F.col("n"), F.col("low"), F.col("high")).alias("least")).toPandas()
    for n, low, high, least in got.itertuples(index=False):
        assert least <= need[n - 1, low - 1 : high].min()


def test_join_of_many_sizes(spark):
    """Passages with three lengths of own words, for many lengths, at both settings."""
    for k, percent in ((3, 90), (5, 80)):
        rows = []
        for passage in range(20, 80, 3):
            for own in range(2, 2 + passage // 6):
                words = [f"{passage}.{i}" for i in range(passage)] + [f"{passage}x{own}.{i}" for i in range(own)]
                rows.append((len(rows), " ".join(words)))
        got = {r[0]: (r[1], r[2]) for r in ngram_join.join(spark.createDataFrame(rows, "doc_id long, text string"), k, percent).collect()}
        assert got == brute_components(rows, k, percent)


REPEAT = " ".join(f"r{i}" for i in range(40))
#: Repeated and null ids with different and equal texts.
TWINS = [
    (5, f"{REPEAT} end", "s1"), (5, f"start {REPEAT}", "s0"), (5, f"start {REPEAT}", "s1"), (None, f"x {REPEAT}", None), (None, "some other words " * 30, "s0"),
    (None, f"y {REPEAT} z", "s1"), (7, "w " * 60, "s2"), (7, "v " * 60, "s2"), (8, f"{REPEAT} end", "s0"), (9, None, "s0"), (9, "", None),
]


def test_substring_dedup_of_repeated_ids(spark):
    import hashlib

    got = Counter((r["doc_id"], r["n_words"], r["n_removed"]) for r in substring_dedup.remove_repeats(spark.createDataFrame(TWINS, "doc_id long, text string, source string"), 20, 3).collect())
    tags = {r["text"]: r["tag"] for r in substring_dedup.keyed(spark.createDataFrame(TWINS, "doc_id long, text string, source string")).collect()}
    distinct = sorted({(d, t) for d, t, _ in TWINS}, key=lambda r: (r[0] is not None, r[0] or 0, tags[r[1]]))
    named = {i: row for i, row in enumerate(distinct)}
    plain = brute_repeats([(i, t or "") for i, (_, t) in named.items()], 20)
    times = Counter((d, t) for d, t, _ in TWINS)
    want = Counter()
    for i, (d, t) in named.items():
        want[d, plain[i][0], plain[i][1]] += times[d, t]
    assert got == want and sum(n for (_, _, gone), n in got.items() if gone) >= 5
    assert hashlib.sha256(b"").hexdigest() in {r["kept_sha256"] for r in substring_dedup.remove_repeats(spark.createDataFrame(TWINS[:2] + TWINS[9:], "doc_id long, text string, source string"), 20).collect()}


def test_one_row_of_each_near_group_stays(spark):
    rows = [*TWINS, (5, f"{REPEAT} end", "s9")]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    kept = ngram_join.kept_rows(df, 5, 80).collect()
    near = [r for r in kept if "r39" in (r["text"] or "")]
    assert len(near) == 1 and near[0]["doc_id"] == 5
    assert Counter(r["doc_id"] for r in kept if "r39" not in (r["text"] or "")) == Counter({None: 1, 7: 2, 9: 2})


def test_mix_keeps_budgets_of_repeated_ids(spark):
    rng = np.random.default_rng(3)
    rows = [(int(rng.integers(0, 20)) if i % 11 else None, " \n".join(f"w{x}" for x in rng.integers(0, 50, rng.integers(0, 40))), f"s{i % 3}") for i in range(400)]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string")
    plan = mixing.mix(df).groupBy("source").agg(F.sum("taken"), F.max("target")).collect()
    words = Counter()
    for r in mixing.apply_mix(df, epoch_col="epoch").collect():
        words[r["source"]] += len(WORD.findall(r["text"]))
        assert r["epoch"] in (1, 2) and any(t.startswith(r["text"]) for _, t, s in rows if s == r["source"])
    assert {r[0]: (r[1], int(r[2])) for r in plan} == {s: (n, n) for s, n in words.items()}


CLASH = ("_l_id", "_k_id", "_m_id", "row", "tag", "id", "sid", "k_id", "size", "_id", "_part", "keep_doc_id", "hits", "k_doc_id", "_copy", "quality", "n", "lang_pred", "mark", "group")


def test_clashing_names_go_through_every_stage(spark, sf):
    rows = [(d, t, "en", s, len(t or "")) for d, t, s in TWINS] + [r[:5] for r in ODD]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long").withColumns({n: F.lit(n) for n in CLASH})
    plain = df.drop(*CLASH)
    for (_, stage), (_, again) in zip(corpus_pipeline.STAGES[:-1], corpus_pipeline.STAGES[:-1], strict=True):
        with_names, without = stage(spark, df, sf), again(spark, plain, sf)
        assert with_names.columns == df.columns
        assert {r[c] for r in with_names.select(*CLASH).distinct().collect() for c in CLASH} <= set(CLASH)
        assert Counter(map(str, with_names.select(*plain.columns).collect())) == Counter(map(str, without.collect()))
    count = lambda f: f(df).count()
    path = public_tokenizers.path("word_bpe_49k.json")
    n = len(rows)
    assert count(ngram_join.join) == count(exact_dedup.groups) == count(mixing.mix) == count(substring_dedup.remove_repeats) == n
    assert count(lambda d: token_counts.count_tokens(d, path)) == count(lambda d: language_id.predict(d, language_id.fit(d, "true"))) == n
    assert count(lambda d: quality_rules.judge(d, quality_rules.fit(d, spark.createDataFrame([(5, 1, "x"), (7, 0, "x")], "doc_id long, quality int, id string")))) == n


def plain_features(line, before):
    words = WORD.findall(line)
    chars, letters = sum(len(w) for w in words), re.findall("[A-Za-z]", line)
    share = lambda a, b: min(1.0, a / max(b, 1))
    return [
        1.0, share(len(re.findall(r"[#*$%&|<>]", line)), len(words)), share(line.count("|"), len(words)), share(line.count("!"), len(words)),
        share(len(re.findall("[A-Z]", line)), len(letters)), share(len(re.findall("[0-9]", line)), chars), 1.0 - len(set(words)) / max(len(words), 1),
        float(line in before), float(len(words) < 5), float(line[-1:] in ".?!" and bool(line)), share(chars, 25 * len(words)),
    ], chars


def plain_verdict(field, text):
    """(content share, labels) of a text by plain Python dynamic programming."""
    lines, before, rows, chars = text.split("\n"), set(), [], []
    for line in lines:
        if WORD.search(line):
            x, n = plain_features(line, before)
            rows.append(x)
            chars.append(n)
            before.add(line)
    if not rows:
        return 0.0, []
    score = [float(np.dot(x, field.weights)) for x in rows]
    best, back = [0.0, score[0]], []
    for s in score[1:]:
        step, came = [], []
        for y in (0, 1):
            a, b = best[0] + field.transitions[0, y], best[1] + field.transitions[1, y]
            came.append(int(b >= a))
            step.append(max(a, b) + (s if y else 0.0))
        back.append(came)
        best = step
    y = int(best[1] >= best[0])
    labels = [y]
    for came in reversed(back):
        y = came[y]
        labels.append(y)
    labels.reverse()
    return sum(c for c, y in zip(chars, labels, strict=True) if y) / sum(chars), labels


def test_quality_verdicts_against_plain_python(spark, sf):
    df = documents(spark, sf)
    field = quality_rules.fit(df, spark.read.parquet(f"{sf}/labels.parquet"))
    got = {r["doc_id"]: r for r in quality_rules.judge(df, field).collect()}
    for r in df.collect():
        share, _ = plain_verdict(field, r["text"] or "")
        assert got[r["doc_id"]]["content_share"] == pytest.approx(share, abs=1e-9)
        assert got[r["doc_id"]]["kept"] == (not got[r["doc_id"]]["base_failed"] and share >= 0.5)


def test_lines_of_mixed_documents(spark):
    """Lines of held-out good and bad documents, shuffled into one: most are told apart, shares lie between."""
    big = "/root/testdata/sf0.01"
    df, labels = documents(spark, big), spark.read.parquet(f"{big}/labels.parquet")
    known = df.join(labels, "doc_id").select("doc_id", "text", "quality").collect()
    held = {r["doc_id"] for r in known if r["doc_id"] % 3 == 0}
    field = quality_rules.fit(df.filter("doc_id % 3 != 0"), labels)
    junk = re.compile(r"(\S+(\*\*\*|\$\$\$|&&&|%%%|###)(\s|$)){3}|( \| .*){3}|([A-ZÀ-Ü.,]+!! ){3}")
    good = [x for r in known if r["doc_id"] in held and r["quality"] == 1 for x in (r["text"] or "").split("\n") if len(x.split()) >= 8 and not junk.search(x)]
    bad = [x for r in known if r["doc_id"] in held and r["quality"] == 0 for x in (r["text"] or "").split("\n") if len(x.split()) >= 8 and junk.search(x)]
    rng = np.random.default_rng(8)
    right = total = between = 0
    texts = []
    for d in range(60):
        parts = [(g, 1) for g in rng.choice(good, 6, replace=False)] + [(b, 0) for b in rng.choice(bad, 5, replace=False)]
        if d % 2:
            rng.shuffle(parts)
            parts = [(str(x), int(y)) for x, y in parts]
        texts.append((d, "\n".join(x for x, _ in parts)))
        share, labels_ = plain_verdict(field, texts[-1][1])
        between += 0 < share < 1
        right += sum(int(a == y) for a, (_, y) in zip(labels_, parts, strict=True))
        total += len(parts)
    assert between >= 55 and right / total > 0.85, (between, right / total)
    shares = [r["content_share"] for r in quality_rules.judge(spark.createDataFrame(texts, "doc_id long, text string"), field).collect()]
    assert sum(0 < s < 1 for s in shares) == between


@settings(max_examples=25, deadline=None)
@given(st.lists(st.tuples(st.lists(st.sampled_from(["<", "/", "s", ">", "[", "INST", "]", "|", "\\", "é", "\n", ":1|>", "image"]), max_size=14).map("".join), st.lists(st.integers(0, 14), max_size=3), st.booleans()), min_size=1, max_size=12))
def test_chat_texts_cut_anywhere(spark_session_for_property, cases):
    """However a text is cut into parts, with or without attachments between, it reads back whole."""
    spark = spark_session_for_property
    rows, want = [], {}
    for conv, (text, cuts, files) in enumerate(cases):
        edges = [0, *sorted(min(c, len(text)) for c in cuts), len(text)]
        parts = []
        for i, (a, b) in enumerate(zip(edges, edges[1:], strict=False)):
            parts.append(("text", text[a:b], None, None, None))
            if files and i + 2 < len(edges):
                parts.append(("image", None, f"f{i}", 14.0, 14.0))
        rows += [(conv, 0, "user", parts), (conv, 1, "assistant", [("text", text, None, None, None)])]
        pieces, n = [], 0
        for kind, t, *_ in parts:
            if kind == "image":
                n += 1
                pieces.append(("image", None, n))
            elif pieces and pieces[-1][0] == "text":
                pieces[-1] = ("text", pieces[-1][1] + t, None)
            elif t:
                pieces.append(("text", t, None))
        want[conv] = (text, pieces)
    df = spark.createDataFrame(rows, f"conv_id long, turn int, role string, parts array<{chat_format.PART}>")
    chats = chat_format.format_chats(df).withColumn("turns", chat_format.read_turns(F.col("formatted"))).withColumn("loss", chat_format.read_loss(F.col("formatted"), F.col("loss_spans")))
    body = F.regexp_extract("formatted", r"(?s)^<s>\[INST\] user \[/INST\] (.*?)</s><s>", 1)
    for r in chats.withColumn("pieces", chat_format.read_parts(body)).collect():
        text, pieces = want[r["conv_id"]]
        assert len(r["turns"]) == 2 and r["turns"][1]["text"] == text and r["loss"] == text
        assert [tuple(p) for p in r["pieces"]] == [p for p in pieces if p[0] != "text" or p[1]]


@pytest.fixture(scope="module")
def spark_session_for_property(spark):
    return spark


def test_fetch_reads_the_frames_asked_for(spark, sf, tmp_path):
    df = documents(spark, sf)
    folder = f"file://{tmp_path}/files"
    manifest = token_files.write_token_files(df, public_tokenizers.path("byte_bpe_50k.json"), 0, folder)
    texts = {r["doc_id"]: r["text"] for r in df.collect()}
    asked = sorted(texts)[3:40:9]
    # Spoil every other frame: a reader that touches one of them fails.
    opened = 0
    for row in manifest.collect():
        path = row["path"].removeprefix("file://")
        raw = bytearray(open(path, "rb").read())
        reader = token_files.ShardReader(io.BytesIO(bytes(raw)), len(raw))
        hit = [k for k, d in enumerate(reader.doc_ids) if d in asked]
        opened += bool(hit)
        for k in range(len(reader)):
            if k not in hit:
                raw[int(reader.starts[k]) + int(reader.packed[k]) - 1] ^= 255
        if not hit:
            raw[-1] ^= 255
        open(path, "wb").write(raw)
    wanted = spark.createDataFrame([(d,) for d in [*asked, asked[0], None, 10**9]], "doc_id long")
    got = {r["doc_id"]: r["ids"] for r in token_files.fetch_documents(manifest, folder, wanted).collect()}
    assert sorted(got) == asked
    for d, ids in zip(asked, brute_ids([texts[d] for d in asked], "byte_bpe_50k.json", 0), strict=True):
        assert got[d] == ids.tolist()


def test_index_reopens_and_replays(spark, sf, tmp_path):
    df = substring_dedup.keyed(documents(spark, sf))
    folder = f"file://{tmp_path}/index"
    part = lambda i: df.filter(F.col("doc_id") % 4 == i)
    spans = {}
    for i in range(4):
        # Opened anew for every batch, as after a restart.
        index = substring_dedup.FingerprintIndex(spark, folder, fan_out=2, buckets=5)
        out = index.add(part(i), df.filter(F.col("doc_id") % 4 < i), batch=f"b{i}")
        spans[i] = sorted(map(str, out.collect()))
        assert sorted(map(str, substring_dedup.FingerprintIndex(spark, folder).add(part(i), None, batch=f"b{i}").collect())) == spans[i]
    index = substring_dedup.FingerprintIndex(spark, folder)
    assert index.compactions == 1 and index.buckets == 5 and len(index.marks) == len(index.windows) == 2
    for run in index.marks:
        assert run.count() == run.select("mark").distinct().count() == spark.read.parquet(run._subvote_path).count()
    names = json.loads(open(f"{tmp_path}/index/manifest-{index.version:08d}.json").read())
    assert len(names["marks"]) == 2 and set(names["results"]) == {"b0", "b1", "b2", "b3"}
    # Batches in this order are documents in the order (id mod 4, id).
    rows = sorted(((r["doc_id"], r["text"] or "") for r in df.collect()), key=lambda r: (r[0] % 4, r[0]))
    plain = brute_repeats([(i, t) for i, (_, t) in enumerate(rows)], 20)
    removed = defaultdict(int)
    for r in (r for i in range(4) for r in substring_dedup.FingerprintIndex(spark, folder).add(part(i), None, batch=f"b{i}").collect()):
        removed[r["doc_id"]] += sum(b - a for a, b in zip(r["starts"], r["ends"], strict=True))
    assert {d: plain[i][1] for i, (d, _) in enumerate(rows) if plain[i][1]} == dict(removed)
    # Merge joins read the runs as they lie: neither shuffled nor sorted.
    spark.conf.set("spark.sql.legacy.bucketedTableScan.outputOrdering", "true")
    try:
        joined = index.marks[0].join(index.marks[1].select("mark").hint("merge"), "mark")
        plan = joined._jdf.queryExecution().executedPlan().toString()
        assert "SortMergeJoin" in plan and "Exchange" not in plan and "Sort [" not in plan
    finally:
        spark.conf.unset("spark.sql.legacy.bucketedTableScan.outputOrdering")
    index.drop()


def test_query_reaches_compaction(spark, sf, monkeypatch):
    seen = []
    compact = substring_dedup.FingerprintIndex._compact
    monkeypatch.setattr(substring_dedup.FingerprintIndex, "_compact", lambda self: (seen.append(len(self.marks)), compact(self))[1])
    queries.op10_substring_dedup(spark, sf)
    assert seen == [3]


def plain_grams(text):
    out = Counter()
    word = ""
    for c in [*text, " "]:
        if c.isalpha():
            low = c.lower()
            word += low if len(low) == 1 else c
        elif word:
            out.update(word)
            for n in (2, 3):
                full = f"\0{word}\0"
                out.update(full[i : i + n] for i in range(len(full) - n + 1))
            word = ""
    return out


def plain_profile(counts, top):
    return [g for g, _ in sorted(counts.items(), key=lambda x: (-x[1], code(x[0])))[:top]]


def code(gram):
    """The order of n-grams: 21 bits a letter, pairs marked by a bit above."""
    out = 0
    for c in gram:
        out = (out << 21) | ord(c)
    return out | (1 << 42 if len(gram) == 2 else 0)


def test_language_against_plain_python(spark, sf):
    got = {r["doc_id"]: r for r in queries.op7_language_id(spark, sf).collect()}
    rows = documents(spark, sf).collect()
    held = lambda d: zlib.crc32(str(d).encode()) % 5 == 0
    counts = defaultdict(Counter)
    for r in rows:
        if not held(r["doc_id"]) and r["lang"] is not None:
            counts[r["lang"]] += plain_grams(r["text"] or "")
    ranked = {lang: {g: i for i, g in enumerate(plain_profile(c, 300))} for lang, c in sorted(counts.items())}
    for r in rows:
        mine = plain_profile(plain_grams(r["text"] or ""), 300)
        out = got[r["doc_id"]]
        assert out["held_out"] == held(r["doc_id"])
        if not mine:
            assert (out["lang_pred"], out["score"]) == ("und", 0.0)
            continue
        far = {lang: sum(min(300, abs(p[g] - i)) if g in p else 300 for i, g in enumerate(mine)) for lang, p in ranked.items()}
        best = min(far, key=lambda x: (far[x], x))
        assert out["lang_pred"] == best and out["score"] == pytest.approx(1 - far[best] / (300 * len(mine)))


def test_many_languages_are_no_error(spark):
    rows = [(i, f"text number {chr(97 + i % 26)} of language", f"l{i % 40}") for i in range(200)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = language_id.fit(df, "true", max_languages=7)
    assert len(model.names) == 7
    assert {r["lang_pred"] for r in language_id.predict(df, model).collect()} <= set(model.names)
