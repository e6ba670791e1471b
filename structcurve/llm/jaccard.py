"""Join of documents whose sets of word runs have a Jaccard similarity of at least a threshold.

Chosen-path join: in each of several independent runs a set picks tokens of its MinHash signature by
a shared random function, and sets that picked the same token meet in a bucket.  Buckets that are small are
compared by brute force on sketches; large ones are split again by further tokens along the path.  A
pair at the threshold meets in one run with probability of about 1 - 1/e or, deeper down, a little less, so the
runs are repeated until the target recall is reached.  Sets that meet and look alike form candidate
groups; inside a group all pairs are verified exactly on the whole sets, which travel once.
"""

from __future__ import annotations

import math
import re
from collections.abc import Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql import types as T

from .common import arrow_map, text_of, written

WORD = re.compile(r"\w+")
POSITIONS = 128
#: Members of a bucket that are compared by brute force, and of a block of a verified group.
BUCKET, BLOCK = 1000, 400
#: Splits of a large bucket before it is compared block by block.
DEPTH = 3
#: Ids that may be sent to all executors (16 bytes each); more are joined by a shuffle.
SENT_IDS = 1_000_000

_GOLD = np.uint64(0x9E3779B97F4A7C15)


def mix(x: np.ndarray) -> np.ndarray:
    """A 64-bit finaliser: xor-shifts and odd multipliers."""
    x = x ^ (x >> np.uint64(30))
    x = x * np.uint64(0xBF58476D1CE4E5B9)
    x = x ^ (x >> np.uint64(27))
    x = x * np.uint64(0x94D049BB133111EB)
    return x ^ (x >> np.uint64(31))


_ODD = mix(np.arange(1, POSITIONS + 1, dtype=np.uint64) * _GOLD) | np.uint64(1)
_PLACE = mix(np.arange(1, POSITIONS + 1, dtype=np.uint64) + _GOLD)


class Shingler:
    """Sets of hashed word runs; words are hashed once per worker."""

    def __init__(self, n: int):
        self.n, self.memo = n, {}

    def __call__(self, text: str) -> np.ndarray:
        import xxhash

        if len(self.memo) > 1_000_000:
            self.memo.clear()
        memo, ids = self.memo, []
        for w in WORD.findall(text.lower()):
            h = memo.get(w)
            if h is None:
                h = memo[w] = xxhash.xxh64_intdigest(w.encode("utf-8", "surrogatepass"))
            ids.append(h)
        if not ids:
            return np.zeros(0, np.uint64)
        word = np.array(ids, np.uint64)
        n = min(self.n, len(word))
        out = word[: len(word) - n + 1].copy()
        for i in range(1, n):
            out = mix(out + _GOLD) ^ word[i : len(word) - n + 1 + i]
        return np.unique(mix(out))


def signature(shingles: np.ndarray) -> np.ndarray:
    """MinHash values, one for each position."""
    low = np.full(POSITIONS, np.iinfo(np.uint64).max, np.uint64)
    for i in range(0, len(shingles), 8192):
        part = (shingles[None, i : i + 8192] ^ _PLACE[:, None]) * _ODD[:, None]
        low = np.minimum(low, part.min(axis=1))
    return mix(low)


def first_keys(sig: np.ndarray, runs: int, threshold: float) -> np.ndarray:
    """Bucket keys of all runs: a token is picked with probability 1 / (threshold * positions)."""
    salt = mix(np.arange(1, runs + 1, dtype=np.uint64) * _GOLD)
    dice = mix((sig ^ _PLACE)[None, :] + salt[:, None])
    limit = np.uint64(int(2.0**64 / (threshold * POSITIONS)) - 1)
    return mix(dice[dice <= limit] + _GOLD)


def next_keys(key: np.uint64, sketch: np.ndarray, threshold: float) -> np.ndarray:
    """Keys one step further along the path, by tokens of the sketch."""
    dice = mix((sketch.astype(np.uint64) ^ _PLACE) + mix(np.array([key], np.uint64)))
    limit = np.uint64(int(2.0**64 / (threshold * POSITIONS)) - 1)
    return mix(dice[dice <= limit] + _GOLD)


def runs_for(recall: float, depth: int = DEPTH) -> int:
    """Runs until a pair at the threshold has met with probability ``recall``.

    One pick per set on average along a path makes a branching process of mean one: its survival after
    each step is 1 - exp(-survival before).
    """
    alive = 1.0
    for _ in range(depth + 1):
        alive = 1 - math.exp(-alive)
    return max(1, math.ceil(math.log(1 - recall) / math.log(1 - alive)))


class Roots:
    """Union-find over 0..n-1 whose roots are the smallest members."""

    def __init__(self, n: int):
        self.up = list(range(n))

    def find(self, i: int) -> int:
        while self.up[i] != i:
            self.up[i] = self.up[self.up[i]]
            i = self.up[i]
        return i

    def join(self, i: int, j: int) -> None:
        a, b = self.find(i), self.find(j)
        if a != b:
            self.up[max(a, b)] = min(a, b)


def alike(sketches: np.ndarray, least: int) -> Roots:
    """Groups of sketches that agree in at least ``least`` positions, all pairs compared."""
    roots = Roots(len(sketches))
    for i in range(len(sketches) - 1):
        same = (sketches[i + 1 :] == sketches[i]).sum(axis=1)
        for j in np.nonzero(same >= least)[0].tolist():
            roots.join(i, i + 1 + j)
    return roots


def intersections(sets: list[np.ndarray]) -> np.ndarray:
    """Sizes of all pairs' intersections: incidence of the shared tokens times its transpose, in strips."""
    n = len(sets)
    owner = np.repeat(np.arange(n), [len(s) for s in sets])
    tokens, inverse, counts = np.unique(np.concatenate(sets), return_inverse=True, return_counts=True)
    common = counts > 1
    column = np.cumsum(common) - 1
    keep = common[inverse]
    owner, column = owner[keep], column[inverse[keep]]
    out = np.zeros((n, n), np.float32)
    order = np.argsort(column, kind="stable")
    owner, column = owner[order], column[order]
    width = 4096
    for lo in range(0, int(common.sum()), width):
        a, b = np.searchsorted(column, [lo, lo + width])
        strip = np.zeros((n, min(width, int(common.sum()) - lo)), np.float32)
        strip[owner[a:b], column[a:b] - lo] = 1
        out += strip @ strip.T
    return out.astype(np.int64)


def linked(sets: list[np.ndarray], threshold: float) -> np.ndarray:
    """Whether each two sets reach the threshold, exactly; nothing links to itself."""
    size = np.array([len(s) for s in sets])
    both = intersections(sets)
    link = both >= threshold * (size[:, None] + size[None, :] - both) - 1e-9
    np.fill_diagonal(link, False)
    return link


def _grouped(batches: Iterator[pa.RecordBatch], keys: int) -> Iterator[pa.Table]:
    """Runs of equal first columns of sorted batches, each as one table."""
    held: list[pa.RecordBatch] = []
    key = None
    for batch in batches:
        if not batch.num_rows:
            continue
        cols = [batch.column(i).to_numpy(zero_copy_only=False) for i in range(keys)]
        change = np.zeros(batch.num_rows, bool)
        for c in cols:
            change[1:] |= c[1:] != c[:-1]
        edges = [0, *np.nonzero(change)[0].tolist(), batch.num_rows]
        for lo, hi in zip(edges, edges[1:]):
            here = tuple(c[lo] for c in cols)
            if here != key and held:
                yield pa.Table.from_batches(held)
                held = []
            key = here
            held.append(batch.slice(lo, hi - lo))
    if held:
        yield pa.Table.from_batches(held)


def components(edges: DataFrame, most: int = 50) -> DataFrame:
    """``node, root``: the smallest node of each node's component, for nodes of ``edges (a, b)``.

    Large-star and small-star rounds; each writes its edges to shared storage.  Two rounds suffice for
    stars, which is what the callers make.
    """
    both = lambda e: e.select("a", "b").union(e.select(F.col("b").alias("a"), F.col("a").alias("b")))
    now = written(edges.where("a <> b").select(F.greatest("a", "b").alias("a"), F.least("a", "b").alias("b")).distinct(), "edges")
    before = None
    for _ in range(most):
        mark = now.agg(F.count("*"), F.coalesce(F.sum(F.xxhash64("a", "b").cast("decimal(38,0)")), F.lit(0).cast("decimal(38,0)"))).first()
        if mark[0] == 0 or mark == before:
            break
        before = mark
        sides = both(now)
        # what is joined back is written first, so that a node with very many edges can be split
        low = written(sides.groupBy("a").agg(F.least(F.min("b"), F.first("a")).alias("m")), "low")
        large = sides.join(low, "a").where("b > a").select(F.col("b").alias("a"), F.col("m").alias("b")).where("a <> b").distinct()
        large = written(large, "large")
        low = written(large.groupBy("a").agg(F.min("b").alias("m")), "low")
        small = large.join(low, "a").select("a", "b", "m")
        now = written(small.select(F.col("b").alias("a"), F.col("m").alias("b")).union(small.select("a", F.col("m").alias("b"))).where("a <> b").distinct(), "edges")
    return now.groupBy(F.col("a").alias("node")).agg(F.min("b").alias("root"))


def head_of(shingles: np.ndarray) -> str:
    """A set's name: 128 bits of hash and its size; empty for the empty set."""
    if not len(shingles):
        return ""
    return f"{int(mix(shingles).sum(dtype=np.uint64)):016x}{int(mix(shingles ^ _GOLD).sum(dtype=np.uint64)):016x}{len(shingles):x}"


def similar_documents(docs: DataFrame, threshold: float = 0.8, shingle: int = 5, recall: float = 0.995, id_col: str = "doc_id", text_col: str = "text") -> DataFrame:
    """One row per document: ``doc_id, class_id, n_links``.

    class_id is the smallest id of the documents joined to it by links, directly or over others; n_links
    is the number of other documents whose set of ``shingle``-word runs (of lower-case words; shorter texts are one
    run) reaches the threshold.  Equal sets are one representative with a count, so copies are never
    expanded; texts without words have equal (empty) sets.  Null ids can name no class: such rows get
    null and 0 links.  Rows, not ids, are documents: repeated rows are copies, and an id on two different
    texts is two documents, each linked by its own text (their classes may both be named by that id).
    Ties go to the smallest id; empty tables give empty tables; other columns are ignored.  Nothing is
    capped: buckets above BUCKET are split, then compared block by block, and groups above BLOCK are
    verified block against block.
    """
    return classified(docs, threshold, shingle, recall, id_col, text_col)[0].select("doc_id", "class_id", "n_links")


def classified(docs: DataFrame, threshold: float = 0.8, shingle: int = 5, recall: float = 0.995, id_col: str = "doc_id", text_col: str = "text") -> tuple[DataFrame, DataFrame]:
    """(``doc_id, head, root, class_id, n_links`` of each row, the ids that occur in several rows).

    Inside, a set goes by ``rep``, a 64-bit hash of its head; that no two share one is checked, and another
    salt is taken if they do.  ``root`` is the smallest rep of the class.
    """
    runs = runs_for(recall)
    rows = docs.select(F.col(id_col).cast("bigint").alias("doc_id"), text_of(text_col).alias("text"))

    def sign(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        cut = Shingler(shingle)
        for batch in batches:
            heads, sketches, keys = [], [], []
            for text in batch.column(1).to_pylist():
                s = cut(text)
                heads.append(head_of(s))
                if len(s):
                    m = signature(s)
                    sketches.append((m & np.uint64(255)).astype(np.uint8).tobytes())
                    keys.append(first_keys(m, runs, threshold).view(np.int64).tolist())
                else:
                    sketches.append(b"")
                    keys.append([])
            yield pa.RecordBatch.from_arrays([batch.column(0), pa.array(heads, pa.string()), pa.array(sketches, pa.binary()), pa.array(keys, pa.list_(pa.int64()))], ["doc_id", "head", "sketch", "keys"])

    signed = written(arrow_map(rows, sign, "doc_id bigint, head string, sketch binary, keys array<bigint>"), "signed")
    known = signed.where("doc_id is not null")
    repeated = written(known.groupBy("doc_id").agg(F.count("*").alias("n")).where("n > 1").select("doc_id"), "repeated-ids")
    unique = repeated.isEmpty()
    heads = written(known.groupBy("head").agg(F.min("doc_id").alias("first_id"), F.count("*").alias("copies")), "heads")
    for salt in range(64):
        tally = heads.withColumn("rep", F.xxhash64("head", F.lit(salt)))
        n = tally.agg(F.count("*").alias("n"), F.count_distinct("rep").alias("reps")).first()
        if n.n == n.reps:
            break
    # of a head, one row of the smallest id; sketch and keys depend on the head alone
    first = tally.select(F.col("head").alias("_h"), F.col("first_id").alias("_i"), "rep")
    reps = known.join(first, (F.col("doc_id") == F.col("_i")) & (F.col("head") == F.col("_h"))).select("rep", "sketch", "keys")
    reps = written(reps if unique else reps.dropDuplicates(["rep"]), "reps")

    pairs = reps.select("rep", F.explode("keys").alias("key"))
    met = pairs.join(_counted(pairs), "key")
    meeting = written(met.join(reps.select("rep", "sketch"), "rep").select("key", "n", "rep", "sketch"), "meeting")
    found = [_compared(meeting.where(F.col("n") <= BUCKET), threshold)]
    large = meeting.where(F.col("n") > BUCKET).select("key", "rep", "sketch")
    for depth in range(DEPTH):
        if large.isEmpty():
            break
        deeper = written(_split(large, threshold), "deeper")
        again = written(deeper.join(_counted(deeper), "key"), "again")
        found.append(_compared(again.where(F.col("n") <= BUCKET), threshold))
        large = again.where(F.col("n") > BUCKET)
        if depth == DEPTH - 1 and not large.isEmpty():
            found.append(_compared(_block_pairs(large, F.ceil(F.col("n") / BUCKET), "rep", ["key"]), threshold))
        large = large.select("key", "rep", "sketch")
    edges = found[0]
    for e in found[1:]:
        edges = edges.union(e)
    groups = components(edges)
    # a root belongs to its own group
    groups = written(groups.union(groups.select(F.col("root").alias("node"), "root").distinct()).distinct(), "groups")
    exact = _verified(rows, tally, groups, shingle, threshold, unique)
    classes = written(components(exact.where("rep <> mate").select(F.col("rep").alias("a"), F.col("mate").alias("b"))).withColumnRenamed("node", "rep"), "classes")
    links = exact.groupBy("rep").agg(F.sum("links").alias("links"))
    # a class is named by its smallest id; its root has no row of its own in classes
    members = classes.union(classes.select(F.col("root").alias("rep"), "root").distinct()).distinct()
    names = members.join(tally.select("rep", "first_id"), "rep").groupBy("root").agg(F.min("first_id").alias("class_id"))
    named = written(members.join(names, "root"), "named")
    per_head = tally.join(links, "rep", "left").join(named, "rep", "left").select("head", F.coalesce("root", "rep").alias("root"), F.coalesce("class_id", "first_id").alias("class_id"), (F.coalesce("links", F.lit(0)) + F.col("copies") - 1).alias("n_links"))
    out = known.select("doc_id", "head").join(per_head, "head").select("doc_id", "head", "root", "class_id", "n_links")
    none = F.lit(None).cast("bigint")
    lost = signed.where("doc_id is null").select("doc_id", "head", none.alias("root"), none.alias("class_id"), F.lit(0).cast("bigint").alias("n_links"))
    return out.union(lost), repeated


def _counted(rows: DataFrame) -> DataFrame:
    """Keys with at least two rows and their number, written: a join with them then has exchanges of its own
    on both sides, which the planner can split where one key has very many rows."""
    return written(rows.groupBy("key").agg(F.count("*").alias("n")).where("n > 1"), "counts")


def _split(rows: DataFrame, threshold: float) -> DataFrame:
    """Members of large buckets, at the next step of their paths."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            keys, reps, sketches = [], [], []
            for key, rep, sketch in zip(*(batch.column(i).to_pylist() for i in range(3))):
                for k in next_keys(np.uint64(key & (1 << 64) - 1), np.frombuffer(sketch, np.uint8), threshold).view(np.int64).tolist():
                    keys.append(k)
                    reps.append(rep)
                    sketches.append(sketch)
            yield pa.RecordBatch.from_arrays([pa.array(keys, pa.int64()), pa.array(reps, pa.int64()), pa.array(sketches, pa.binary())], ["key", "rep", "sketch"])

    return arrow_map(rows, run, "key bigint, rep bigint, sketch binary").distinct()


def _block_pairs(rows: DataFrame, blocks, member: str, group: list[str]) -> DataFrame:
    """Each member once for each pair of blocks with its own: ``block`` numbers the pair (low * blocks + high)."""
    own = F.pmod(F.xxhash64(F.col(member)), F.col("_blocks"))
    dealt = rows.withColumn("_blocks", blocks.cast("bigint")).withColumn("own", own)
    other = F.explode(F.sequence(F.lit(0).cast("bigint"), F.col("_blocks") - 1)).alias("_other")
    return dealt.select("*", other).withColumn("block", F.least("own", "_other") * F.col("_blocks") + F.greatest("own", "_other")).drop("_other", "_blocks")


def _compared(rows: DataFrame, threshold: float) -> DataFrame:
    """Edges (a, b) from members of a bucket to the smallest member of those that look alike.

    The sketch's agreement is held 0.12 below the threshold, over three standard deviations of its error.
    """
    least = int(math.ceil((threshold - 0.12) * POSITIONS))
    if "block" not in rows.columns:
        rows = rows.withColumn("block", F.lit(0).cast("bigint"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        a: list[int] = []
        b: list[int] = []
        for t in _grouped(batches, 2):
            if t.num_rows > 1:
                reps = t.column("rep").to_pylist()
                roots = alike(np.frombuffer(b"".join(t.column("sketch").to_pylist()), np.uint8).reshape(-1, POSITIONS), least)
                for i in range(len(reps)):
                    if (j := roots.find(i)) != i:
                        a.append(reps[i])
                        b.append(reps[j])
            if len(a) > 10_000:
                yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])
                a, b = [], []
        yield pa.RecordBatch.from_arrays([pa.array(a, pa.int64()), pa.array(b, pa.int64())], ["a", "b"])

    dealt = rows.select("key", "block", "rep", "sketch").repartition("key", "block").sortWithinPartitions("key", "block", "rep")
    return arrow_map(dealt, run, "a bigint, b bigint").distinct()


def _verified(rows: DataFrame, tally: DataFrame, groups: DataFrame, shingle: int, threshold: float, unique: bool) -> DataFrame:
    """``rep, mate, links``: linked copies found in one pair of blocks, and the smallest member linked there.

    A set is cut again from a text of the head's smallest id; where ids are not ``unique`` its head tells which.
    """
    size = written(groups.groupBy("root").agg(F.count("*").alias("n")), "group-sizes")
    members = groups.join(size, "root").withColumnRenamed("node", "rep").join(tally, "rep")
    members = written(members, "members")
    few = members.count() <= SENT_IDS
    plan = members.select(F.col("first_id").alias("doc_id"), "root", "rep", "n", "copies", "head")
    texts = rows.join(F.broadcast(plan) if few else plan, "doc_id")

    def cut(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Shingler(shingle)
        for batch in batches:
            sets = [make(t) for t in batch.column(5).to_pylist()]
            right = pa.array([head_of(s) == h for s, h in zip(sets, batch.column(4).to_pylist())], pa.bool_())
            yield pa.RecordBatch.from_arrays([*(batch.column(i) for i in range(4)), pa.array([s.tobytes() for s in sets], pa.binary())], ["root", "rep", "n", "copies", "set"]).filter(right)

    sets = arrow_map(texts.select("root", "rep", "n", "copies", "head", "text"), cut, "root bigint, rep bigint, n bigint, copies bigint, set binary")
    if not unique:
        sets = sets.dropDuplicates(["root", "rep"])
    dealt = _block_pairs(sets, F.ceil(F.col("n") / BLOCK), "rep", ["root"]).select("root", "block", "rep", "own", "copies", "set")

    def verify(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        out: list[tuple[int, int, int]] = []
        for t in _grouped(batches, 2):
            if t.num_rows > 1:
                reps, own = t.column("rep").to_pylist(), np.array(t.column("own").to_pylist())
                copies = np.array(t.column("copies").to_pylist())
                link = linked([np.frombuffer(s, np.uint64) for s in t.column("set").to_pylist()], threshold)
                if own.min() != own.max():
                    link &= own[:, None] != own[None, :]
                order = np.argsort(reps)
                roots = Roots(len(reps))
                place = np.empty(len(reps), np.int64)
                place[order] = np.arange(len(reps))
                for i, j in zip(*np.nonzero(np.triu(link))):
                    roots.join(int(place[i]), int(place[j]))
                n = link @ copies
                for i in np.nonzero(n)[0].tolist():
                    out.append((reps[i], reps[order[roots.find(int(place[i]))]], int(n[i])))
            if len(out) > 10_000:
                yield _links(out)
                out = []
        yield _links(out)

    spread = dealt.repartition("root", "block").sortWithinPartitions("root", "block", "rep")
    return written(arrow_map(spread, verify, "rep bigint, mate bigint, links bigint"), "links")


def _links(rows: list[tuple[int, int, int]]) -> pa.RecordBatch:
    return pa.RecordBatch.from_arrays([pa.array([r[i] for r in rows], pa.int64()) for i in range(3)], ["rep", "mate", "links"])


def keep_one(docs: DataFrame, id_col: str = "doc_id", text_col: str = "text", **options) -> DataFrame:
    """The documents without all but the smallest id of each class; all columns kept as they were.

    Rows with a null id stay, all of them.  Null and empty texts, and those without a word, are one class.
    Repeated rows stay once.  An id on different texts is several documents: each goes or stays by its own
    class (ties of ids inside a class: the smallest head), so no text is lost unless one like it stays.
    Columns may have any names; an empty table stays empty.  Where no id repeats, the ids that go are joined
    out (sent to all where a count shows them few) and documents are not shuffled; the rows of
    repeated ids alone are told apart by their texts.
    """
    found, repeated = classified(docs, id_col=id_col, text_col=text_col, **options)
    found = written(found, "classes").where("doc_id is not null")
    extra = written(found.where("doc_id <> class_id").select(F.col("doc_id").alias("id")).distinct(), "extra-ids")
    few = extra.count() <= SENT_IDS  # then the documents themselves need not be shuffled
    whole = docs.select(F.struct(*(docs[f"`{c}`"] for c in docs.columns)).alias("row"), docs[f"`{id_col}`"].cast("bigint").alias("id"), text_of(text_col).alias("text"))
    if repeated.isEmpty():
        return whole.join(F.broadcast(extra) if few else extra, "id", "left_anti").select("row.*")
    several = repeated.select(F.col("doc_id").alias("id"))
    once = whole.join(several, "id", "left_anti").join(F.broadcast(extra) if few else extra, "id", "left_anti")
    shingle = options.get("shingle", 5)

    def name(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        make = Shingler(shingle)
        for batch in batches:
            heads = pa.array([head_of(make(t)) for t in batch.column(2).to_pylist()], pa.string())
            yield pa.RecordBatch.from_arrays([batch.column(0), batch.column(1), heads], ["row", "id", "head"])

    rows = whole.join(several, "id", "left_semi").select("row", "id", "text")
    schema = T.StructType([T.StructField("row", rows.schema["row"].dataType), T.StructField("id", T.LongType()), T.StructField("head", T.StringType())])
    first = found.join(repeated, "doc_id", "left_semi").where("doc_id = class_id").groupBy("root").agg(F.min(F.struct("doc_id", "head")).alias("f"))
    first = first.select(F.col("f.doc_id").alias("id"), F.col("f.head").alias("head"))
    chosen = arrow_map(rows, name, schema).join(first, ["id", "head"], "left_semi").dropDuplicates(["id", "head"])
    return once.select("row.*").union(chosen.select("row.*"))
