"""N-gram Jaccard join through a token-group matrix, exact.

A document's set is its distinct k-word shingles.  Equal sets are one node.  Tokens are
ordered from rare to frequent by a fixed-size count sketch of the whole corpus, and two
sets can only link if the first few tokens of both (their prefixes) meet.  Sets whose
prefix meets no other drop out; the rest go through the matrix:

1. partition: a set joins the group of the prefix token it shares with most sets, cut by size;
   the matrix holds the prefix tokens of each group, and sets that agree with no group in
   as many tokens as a link requires drop out;
2. within a group, every set is compared with a few leaders, which links most copies;
3. a set that agrees with another group often enough in the matrix is bounded by its overlap
   with the stored union of that group's whole sets, and the group is opened only if the
   bound reaches the threshold;
4. opened groups are compared in blocks of bounded volume; what a leader has joined already
   is not compared again, and a block returns the links that join components, never all pairs.

Every step is a table in the shared folder.  Tokens are 56-bit hashes under their frequency
level; sets are told apart by 128 bits over a second, independent hash of their words.

Defined cases: null, empty and word-less texts have an empty set and no links; texts with
fewer than k words have the whole sequence as one shingle; null ids are kept, sort first
and never name a component unless it has no other id; repeated rows are equal sets; an
empty table gives no rows; other columns are ignored.
"""

from __future__ import annotations

import math
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from subvote.llm._store import discard, materialize, text_tag, whole_row
from subvote.llm._text import U64, Words, as_long, list_array, mix64, roll, text_slices
from subvote.llm.components import components
from subvote.llm._worker import tidied

SKETCH_BITS, BLOCK_BITS = 21, 15
#: Tokens and sets of one block of an opened group, about.
BLOCK_TOKENS, BLOCK_SETS = 100_000, 256


def shingles(buf: np.ndarray, offs: np.ndarray, k: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, token) of every shingle with repeats, in document order."""
    words = Words(buf, offs, lower=True)
    return word_runs(words, k, 0)


def word_runs(words: Words, k: int, salt: int) -> tuple[np.ndarray, np.ndarray]:
    """(document, hash) of every run of k words, or of all words where a document has fewer."""
    at = words.windows(k)
    tokens = roll(words.hashed(salt), k, salt)[at] if len(at) else np.empty(0, U64)
    doc = words.doc[at]
    few = np.flatnonzero((words.counts > 0) & (words.counts < k))
    if len(few):
        first, count, h = words.first[few], words.counts[few], words.hashed(salt)
        whole = np.zeros(len(few), U64)
        for j in range(k - 1):
            here = count > j
            whole[here] = mix64(whole[here] ^ h[first[here] + j], 31 + j + salt)
        whole = mix64(whole + count.astype(U64), 77 + salt)
        doc, tokens = np.concatenate([doc, few]), np.concatenate([tokens, whole])
        order = np.argsort(doc, kind="stable")
        doc, tokens = doc[order], tokens[order]
    return doc, tokens


def token_sets(buf: np.ndarray, offs: np.ndarray, k: int, levels: np.ndarray) -> tuple[list[np.ndarray], list[bytes | None]]:
    """Of every document: its ordered set (distinct tokens, rare ones first) and the set's name."""
    words = Words(buf, offs, lower=True)
    doc, tokens = word_runs(words, k, 0)
    _, second = word_runs(words, k, 40)
    level = levels[(tokens & U64((1 << SKETCH_BITS) - 1)).astype(np.int64)].astype(U64)
    keys = (level << U64(56)) | (tokens >> U64(8))
    cuts = np.searchsorted(doc, np.arange(1, len(offs) - 1))
    sets, names = [], []
    for x, y in zip(np.split(keys, cuts), np.split(second, cuts), strict=True):
        found, at = np.unique(x, return_index=True)
        sets.append(found)
        names.append(set_id(found, y[at]))
    return sets, names


def frequency_levels(docs: DataFrame, k: int, text_col: str) -> np.ndarray:
    """Level (about twice the binary logarithm of the count) of every cell of the sketch.

    Tasks send their counters in blocks; two rounds of sums keep every task's input to a
    share of the blocks.  What comes back is 2**SKETCH_BITS bytes, whatever the input.
    """
    blocks, width = 1 << (SKETCH_BITS - BLOCK_BITS), 1 << BLOCK_BITS

    @tidied
    def count(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros(1 << SKETCH_BITS, np.int64)
        for batch in batches:
            for _, _, buf, offs in text_slices(batch.column(0)):
                _, tokens = shingles(buf, offs, k)
                total += np.bincount((tokens & U64((1 << SKETCH_BITS) - 1)).astype(np.int64), minlength=len(total))
        if total.any():
            salt = int(total[:4096].sum()) % 64
            packed = [np.minimum(total[i * width : (i + 1) * width], 65535).astype("<u2").tobytes() for i in range(blocks)]
            yield pa.RecordBatch.from_pydict({"block": pa.array(range(blocks), pa.int32()), "salt": pa.array([salt] * blocks, pa.int32()), "counts": pa.array(packed, pa.binary())})

    def add(kind: str, pack):
        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            sums: dict[int, np.ndarray] = {}
            for batch in batches:
                for block, raw in zip(batch.column("block").to_pylist(), batch.column("counts"), strict=True):
                    one = np.frombuffer(raw.as_buffer(), kind)
                    sums[block] = sums[block] + one if block in sums else one.astype(np.int64)
            for block, one in sums.items():
                yield pa.RecordBatch.from_pydict({"block": pa.array([block], pa.int32()), "salt": pa.array([0], pa.int32()), "counts": pa.array([pack(one)], pa.binary())})

        return run

    def small(total: np.ndarray) -> bytes:
        return (2 * np.log2(np.maximum(total, 1))).astype(np.uint8).tobytes()

    schema = "block int, salt int, counts binary"
    partial = docs.select(text_col).mapInArrow(count, schema).repartition(blocks, "block", "salt").mapInArrow(add("<u2", lambda x: x.tobytes()), schema)
    total = partial.repartition(blocks, "block").mapInArrow(add("<i8", small), schema)
    level = np.zeros(1 << SKETCH_BITS, np.uint8)
    for row in total.collect():
        level[row["block"] * width : (row["block"] + 1) * width] = np.frombuffer(row["counts"], np.uint8)
    return level


def _needed(n, percent: int):
    """Smallest overlap with which a set of n tokens can link."""
    return (percent * n + 99) // 100


def _fits(a: Column, b: Column, percent: int) -> Column:
    return (F.least(a, b) * 100) >= (F.greatest(a, b) * percent)


class Join:
    """One run of the join over a table; see the module's description for the steps."""

    def __init__(self, docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text", leaders: int = 3):
        self.spark, self.k, self.percent, self.leaders = docs.sparkSession, k, percent, leaders
        self.tables: list[DataFrame] = []
        self.docs = docs.select(F.col(id_col).cast("long").alias("doc_id"), F.col(text_col).alias("text"), text_tag(F.col(text_col)).alias("tag"))

    def _table(self, df: DataFrame, name: str) -> DataFrame:
        """A table that is deleted once the join is through."""
        self.tables.append(materialize(df, name))
        return self.tables[-1]

    def rows(self) -> tuple[DataFrame, DataFrame]:
        """(doc_id, tag, n, sid) of every row, and (sid, root, component_id) of every set."""
        levels = frequency_levels(self.docs, self.k, "text")
        self.levels = self.spark.sparkContext.broadcast(levels)  # 2 MB, fixed
        rows = materialize(self._prefixes(), "join-rows")
        sets = self._table(
            rows.filter("n > 0").groupBy("sid").agg(F.min("doc_id").alias("least"), F.min(F.struct("doc_id", "tag")).alias("at"), F.first("n").alias("n"), F.first("prefix").alias("prefix")), "join-sets"
        )
        meeting = self._meeting(sets)
        roots = self._roots(sets, meeting)
        named = sets.select("sid", "least").join(roots, "sid", "left").withColumn("root", F.coalesce("root", "sid"))
        names = named.groupBy("root").agg(F.min("least").alias("component_id"))
        named = materialize(named.join(names, "root").select("sid", "root", "component_id"), "join-named")
        for table in self.tables:
            discard(table)
        return rows.drop("prefix"), named

    def run(self) -> DataFrame:
        """doc_id, n_shingles, component_id."""
        rows, named = self.rows()
        out = rows.select("doc_id", "n", "sid").join(named.drop("root"), "sid", "left")
        return out.select("doc_id", F.col("n").alias("n_shingles"), F.coalesce("component_id", "doc_id").alias("component_id"))

    def _prefixes(self) -> DataFrame:
        k, percent, levels = self.k, self.percent, self.levels

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for lo, hi, buf, offs in text_slices(batch.column(1)):
                    found, names = token_sets(buf, offs, k, levels.value)
                    n = np.fromiter((len(x) for x in found), np.int64, len(found))
                    size = np.where(n > 0, n - _needed(n, percent) + 1, 0)
                    prefix = np.concatenate([x[:s] for x, s in zip(found, size, strict=True)]) if len(found) else np.empty(0, U64)
                    yield pa.RecordBatch.from_arrays(
                        [*(batch.column(c).slice(lo, hi - lo) for c in (0, 2)), pa.array(n), pa.array(names, pa.binary()), list_array(size, as_long(prefix), pa.int64())],
                        ["doc_id", "tag", "n", "sid", "prefix"],
                    )

        return self.docs.mapInArrow(run, "doc_id long, tag long, n long, sid binary, prefix array<long>")

    def _meeting(self, sets: DataFrame) -> DataFrame:
        """(token, sid, n, group) of prefix tokens that two or more sets hold.

        The group of a set is the token it shares with most others, cut by size: sizes of
        one group lie within a few hundredths of each other.
        """
        postings = sets.select("sid", "n", F.explode("prefix").alias("token"))
        shared = postings.groupBy("token").agg(F.count("*").alias("held")).filter("held > 1")
        met = self._table(postings.join(shared, "token"), "join-met")
        best = met.groupBy("sid").agg(F.max(F.struct("held", "token")).alias("best"), F.first("n").alias("size"))
        width = math.log(100 / self.percent) / 2
        best = best.select("sid", F.xxhash64("best.token", F.floor(F.log("size") / width)).alias("group"))
        out = self._table(met.join(best, "sid").select("token", "sid", "n", "group"), "join-meeting")
        discard(met)
        return out

    def _required(self, a: Column, b: Column) -> Column:
        """Prefix tokens that sets of sizes a and b must share at least if they link."""
        p = self.percent
        overlap_ = F.ceil((a + b) * p / (100 + p) - 1e-9)
        return overlap_ - F.ceil(F.greatest(a, b) * p / 100 - 1e-9) + 1

    def _least_required(self, n: Column, low: Column, high: Column) -> Column:
        """Lower bound of `_required(n, b)` over all sizes b from low to high.

        Up to n it is least at the low end; above n its two ceilings make it rise and fall,
        but it stays above the value without them, which is least at the high end (in whole
        numbers, so that no rounding lifts it).
        """
        p = self.percent
        above = F.floor(p * (100 * n - p * high) / (100 * (100 + p))) + 1
        return F.when(high <= n, self._required(n, low)).when(low > n, above).otherwise(F.least(self._required(n, low), above))

    def _surviving(self, meeting: DataFrame) -> DataFrame:
        """(sid, n, mine, group): sets and groups whose rows in the matrix agree often enough.

        The matrix has a row per (token, group); a set agrees with a group in the prefix
        tokens that some other set of the group holds.
        """
        p = self.percent
        ranges = meeting.groupBy("group").agg(F.min("n").alias("n_min"), F.max("n").alias("n_max"))
        matrix = meeting.groupBy("token", "group").agg(F.count("*").alias("times")).join(ranges, "group")
        low, high = F.greatest(F.col("n_min"), F.ceil(F.col("n") * p / 100 - 1e-9)), F.least(F.col("n_max"), F.floor(F.col("n") * 100 / p + 1e-9))
        queries = meeting.select("token", "sid", "n", F.col("group").alias("mine"))
        agree = queries.join(matrix, "token").filter((low <= high) & ((F.col("group") != F.col("mine")) | (F.col("times") > 1)))
        agree = agree.withColumn("required", self._least_required(F.col("n"), low, high)).groupBy("sid", "n", "mine", "group", "required").agg(F.count("*").alias("common"))
        return agree.filter(F.col("common") >= F.col("required")).select("sid", "n", "mine", "group")

    def _roots(self, sets: DataFrame, meeting: DataFrame) -> DataFrame:
        """(sid, root) of the sets that meet others: the least set of their component."""
        percent = self.percent
        surviving = self._table(self._surviving(meeting), "join-surviving")
        members = self._table(surviving.select("sid", "n", F.col("mine").alias("group")).distinct(), "join-members")
        full = self._full_sets(sets, members)
        # Leaders of a group: two drawn by hash, and the set that agrees with most tokens of others.
        lead = members.withColumn("draw", F.struct(F.xxhash64("sid"), "sid", "n"))
        lead = lead.groupBy("group").agg(F.min("draw").alias("a"), F.max("draw").alias("b"))
        central = meeting.join(members.select("sid"), "sid", "left_semi").groupBy("group", "sid", "n").agg(F.count("*").alias("tokens"))
        central = central.groupBy("group").agg(F.max(F.struct("tokens", "sid", "n")).alias("c"))
        lead = lead.join(central, "group")
        picks = F.explode(F.array(*[F.struct(F.col(f"{x}.sid").alias("sid"), F.col(f"{x}.n").alias("n")) for x in ("a", "b", "c")][: self.leaders]))
        lead = lead.select("group", picks.alias("lead"))
        pairs = members.join(lead, "group").filter((F.col("sid") != F.col("lead.sid")) & _fits(F.col("n"), F.col("lead.n"), percent))
        pairs = pairs.select(F.least("sid", "lead.sid").alias("a"), F.greatest("sid", "lead.sid").alias("b")).distinct()
        star = self._table(self._verify(pairs, full), "join-star")

        roots = components(star, "join-roots")
        members = members.join(roots.withColumnRenamed("node", "sid"), "sid", "left").withColumn("root", F.coalesce("root", "sid"))
        members = self._table(members, "join-rooted")
        opened = self._table(self._candidates(surviving, members, full), "join-opened")
        if opened.isEmpty():
            return members.select("sid", "root")
        # Opened groups join whole components of the leaders' links, so only their roots are linked anew.
        ends = lambda side: members.select(F.col("sid").alias(side), F.col("root").alias(f"{side}_root"))
        found = self._open(opened, members, full).join(ends("a"), "a").join(ends("b"), "b")
        tops = components(found.select(F.col("a_root").alias("a"), F.col("b_root").alias("b")), "join-components")
        tops = tops.select(F.col("node").alias("root"), F.col("root").alias("top"))
        return members.select("sid", "root").join(tops, "root", "left").select("sid", F.coalesce("top", "root").alias("root"))

    def _full_sets(self, sets: DataFrame, members: DataFrame) -> DataFrame:
        """(sid, tokens) of the sets that meet others, from their texts."""
        k, levels = self.k, self.levels
        chosen = sets.join(members.select("sid").distinct(), "sid", "left_semi").select(F.col("at.doc_id").alias("at_id"), F.col("at.tag").alias("at_tag")).distinct()

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                for _, _, buf, offs in text_slices(batch.column(0)):
                    found, names = token_sets(buf, offs, k, levels.value)
                    rows = [(x, s) for x, s in zip(found, names, strict=True) if s is not None]
                    if rows:
                        yield pa.RecordBatch.from_arrays([pa.array([s for _, s in rows], pa.binary()), pa.array([x.tobytes() for x, _ in rows], pa.binary())], ["sid", "tokens"])

        texts = self.docs.join(chosen, F.col("doc_id").eqNullSafe(F.col("at_id")) & (F.col("tag") == F.col("at_tag")), "left_semi").select("text")
        return self._table(texts.mapInArrow(run, "sid binary, tokens binary").dropDuplicates(["sid"]), "join-full")

    def _verify(self, pairs: DataFrame, full: DataFrame) -> DataFrame:
        """Pairs (a, b) whose sets link."""
        percent = self.percent
        both = pairs.join(full.select(F.col("sid").alias("a"), F.col("tokens").alias("left")), "a")
        both = both.join(full.select(F.col("sid").alias("b"), F.col("tokens").alias("right")), "b").select("a", "b", "left", "right")

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keep = []
                for x, y in zip(batch.column(2), batch.column(3), strict=True):
                    p, q = np.frombuffer(x.as_buffer(), U64), np.frombuffer(y.as_buffer(), U64)
                    common = overlap(p, q)
                    keep.append(100 * common >= percent * (len(p) + len(q) - common))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["a", "b"]).filter(pa.array(keep, pa.bool_()))

        return both.mapInArrow(run, "a binary, b binary")

    def _candidates(self, surviving: DataFrame, members: DataFrame, full: DataFrame) -> DataFrame:
        """(sid, group) to open: own groups not yet of one component, others by their union."""
        # Own group: sets outside the component that holds most of it.
        held = members.groupBy("group", "root").agg(F.count("*").alias("n_root"))
        main = held.groupBy("group").agg(F.max(F.struct("n_root", "root")).alias("main"), F.count("*").alias("n_roots")).filter("n_roots > 1")
        own = members.join(main, "group").filter(F.col("root") != F.col("main.root")).select("sid", "group")
        # Other groups, from one side of each pair of groups, unless all of it is joined already.
        ends = members.groupBy("group").agg(F.min("root").alias("root_min"), F.max("root").alias("root_max"))
        met = surviving.filter(F.col("group") > F.col("mine")).join(members.select("sid", "root"), "sid").join(ends, "group")
        met = met.filter(~((F.col("root_min") == F.col("root")) & (F.col("root_max") == F.col("root"))))
        met = self._table(met.select("sid", "group").distinct(), "join-met-groups")
        if met.isEmpty():
            return own
        unions = self._unions(members.join(met.select("group").distinct(), "group", "left_semi"), full)
        return own.union(self._bound(met, unions, full))

    def _unions(self, members: DataFrame, full: DataFrame) -> DataFrame:
        """(group, tokens): the union of whole sets, merged within tasks and then per group."""

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                parts: dict[int, list[np.ndarray]] = {}
                for g, raw in zip(batch.column(0).to_pylist(), batch.column(1), strict=True):
                    parts.setdefault(g, []).append(np.frombuffer(raw.as_buffer(), U64))
                if parts:
                    yield pa.RecordBatch.from_arrays([pa.array(list(parts), pa.int64()), pa.array([np.unique(np.concatenate(x)).tobytes() for x in parts.values()], pa.binary())], ["group", "tokens"])

        def merge(part: pa.Table) -> pa.Table:
            whole = np.empty(0, U64)
            for raw in part.column("tokens"):
                whole = np.union1d(whole, np.frombuffer(raw.as_buffer(), U64))
            return pa.table({"group": part.column("group").slice(0, 1), "tokens": pa.array([whole.tobytes()], pa.binary())})

        schema = "group long, tokens binary"
        parts = members.join(full, "sid").select("group", "tokens").mapInArrow(run, schema)
        return self._table(parts.groupBy("group").applyInArrow(merge, schema), "join-unions")

    def _bound(self, met: DataFrame, unions: DataFrame, full: DataFrame) -> DataFrame:
        percent = self.percent
        both = met.join(full, "sid").join(unions.select("group", F.col("tokens").alias("union")), "group").select("sid", "group", "tokens", "union")

        @tidied
        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                keep = []
                for x, y in zip(batch.column(2), batch.column(3), strict=True):
                    p = np.frombuffer(x.as_buffer(), U64)
                    keep.append(overlap(p, np.frombuffer(y.as_buffer(), U64)) >= _needed(len(p), percent))
                yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1)], ["sid", "group"]).filter(pa.array(keep, pa.bool_()))

        return both.mapInArrow(run, "sid binary, group long")

    def _open(self, opened: DataFrame, members: DataFrame, full: DataFrame) -> DataFrame:
        """Compare the sets that open a group with its members, block by block."""
        percent = self.percent
        sized = members.join(opened.select("group").distinct(), "group", "left_semi")
        blocks = lambda df, name: df.groupBy("group").agg(F.ceil(F.greatest(F.sum("n") / BLOCK_TOKENS, F.count("*") / BLOCK_SETS)).cast("int").alias(name))
        asking = opened.join(members.select("sid", "n", "root"), "sid")
        counts = blocks(asking, "n_q").join(blocks(sized, "n_m"), "group")
        cell = lambda name: F.pmod(F.xxhash64("sid", F.lit(7)), F.col(name)).cast("int")
        every = lambda name: F.explode(F.sequence(F.lit(0), F.col(name) - 1))
        q = asking.join(counts, "group").withColumn("qb", cell("n_q")).withColumn("mb", every("n_m")).join(full, "sid")
        m = sized.join(counts, "group").withColumn("mb", cell("n_m")).withColumn("qb", every("n_q")).join(full, "sid")
        # Both sides read the same tables: fresh names for the columns of each.
        columns = [F.col(c).alias(c) for c in ("group", "qb", "mb", "sid", "root", "tokens")]

        def compare(left: pa.Table, right: pa.Table) -> pa.Table:
            found = block_links(left, right, percent) if len(left) and len(right) else []
            return pa.table({"a": pa.array([a for a, _ in found], pa.binary()), "b": pa.array([b for _, b in found], pa.binary())})

        return q.select(columns).groupBy("group", "qb", "mb").cogroup(m.select(columns).groupBy("group", "qb", "mb")).applyInArrow(compare, "a binary, b binary").distinct()


def set_id(tokens: np.ndarray, second: np.ndarray) -> bytes | None:
    """128 bits of a set from both hashes of its shingles, whatever the order; empty sets have none."""
    if not len(tokens):
        return None
    both = second ^ mix64(tokens, 1)
    return np.array([mix64(both, 2).sum(dtype=U64), mix64(second, 3).sum(dtype=U64)], "<u8").tobytes()


def overlap(p: np.ndarray, q: np.ndarray) -> int:
    """Size of the intersection of two sorted distinct arrays."""
    if len(p) > len(q):
        p, q = q, p
    if not len(p):
        return 0
    at = np.searchsorted(q, p)
    at[at == len(q)] = 0
    return int((q[at] == p).sum())


def block_links(asking: pa.Table, members: pa.Table, percent: int) -> list[tuple[bytes, bytes]]:
    """Links between two blocks that join components; at most one per component joined."""
    read = lambda t: [np.frombuffer(x.as_buffer(), U64) for x in t.column("tokens")]
    left, right = read(asking), read(members)
    names, roots = members.column("sid").to_pylist(), members.column("root").to_pylist()
    size = np.fromiter((len(x) for x in right), np.int64, len(right))
    tokens = np.concatenate(right)
    owner = np.repeat(np.arange(len(right)), size)
    order = np.argsort(tokens, kind="stable")
    tokens, owner = tokens[order], owner[order]
    parent: dict[bytes, bytes] = {}

    def top(x: bytes) -> bytes:
        while parent.get(x, x) != x:
            x = parent[x]
        return x

    out = []
    for name, root, mine in zip(asking.column("sid").to_pylist(), asking.column("root").to_pylist(), left, strict=True):
        lo, hi = np.searchsorted(tokens, mine, "left"), np.searchsorted(tokens, mine, "right")
        n = hi - lo
        hits = np.repeat(lo - (np.cumsum(n) - n), n) + np.arange(int(n.sum()))
        common = np.bincount(owner[hits], minlength=len(right))
        for j in np.flatnonzero(100 * common >= percent * (len(mine) + size - common)):
            a, b = top(root), top(roots[j])
            if a != b:
                parent[max(a, b)] = min(a, b)
                out.append((min(name, names[j]), max(name, names[j])))
    return out


def join(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """doc_id, n_shingles, component_id of every row: sets of k words, Jaccard >= percent / 100."""
    return Join(docs, k, percent, id_col, text_col).run()


def kept_rows(docs: DataFrame, k: int = 5, percent: int = 80, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """The rows of `docs` that name their component, and those without one: one of each group."""
    rows, named = Join(docs, k, percent, id_col, text_col).rows()
    same = rows.filter("n > 0").groupBy("sid", "doc_id", "tag").agg(F.count("*").alias("times")).join(named, "sid")
    # Of a component, the row with the least id (null last), then text; of equal rows, one.
    best = F.min(F.struct(F.col("doc_id").isNull().alias("none"), "doc_id", "tag", "times"))
    keep = same.groupBy("root").agg(best.alias("best")).select("best.doc_id", "best.tag", "best.times")
    alone = rows.filter("n = 0").select("doc_id", "tag").distinct().withColumn("times", F.lit(1).cast("long"))
    keep = materialize(keep.unionByName(alone).select(*[F.col(c).alias(f"keep_{c}") for c in ("doc_id", "tag", "times")]), "join-kept")
    own = docs.select(whole_row(), F.col(id_col).cast("long").alias("doc_id"), text_tag(F.col(text_col)).alias("tag"))
    stay = own.join(keep, F.col("doc_id").eqNullSafe(F.col("keep_doc_id")) & (F.col("tag") == F.col("keep_tag")))
    once = stay.filter("keep_times = 1").select("row")
    return once.unionByName(stay.filter("keep_times > 1").dropDuplicates(["doc_id", "tag"]).select("row")).select("row.*")
