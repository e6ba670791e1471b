import pytest
from pyspark.sql import functions as F

from structcurve.llm import mixing as M


def water(sizes, share=1.5, cap=2.0, weights=(3, 1, 2)):
    """Targets by giving the excess away again and again."""
    names = sorted((s for s in sizes if s is not None), key=lambda s: [ord(c) for c in s]) + ([None] if None in sizes else [])
    w = {s: weights[i % len(weights)] for i, s in enumerate(names)}
    full, left = {}, share * sum(sizes.values())
    while True:
        open_ = [s for s in names if s not in full]
        total = sum(w[s] for s in open_)
        share_of = {s: left * w[s] / total for s in open_}
        over = [s for s in open_ if share_of[s] > cap * sizes[s]]
        if not over:
            return full | share_of
        for s in over:
            full[s] = cap * sizes[s]
            left -= full[s]


@pytest.mark.parametrize("sizes", [{"a": 100, "b": 100, "c": 100}, {"a": 10, "b": 5000, "c": 20, None: 700, "é": 3, "Z": 90}, {"a": 0, "b": 7}])
def test_targets(spark, sizes):
    rows = spark.createDataFrame(list(sizes.items()), "source string, source_size bigint")
    got = {r.source: r.target for r in M.source_targets(rows).collect()}
    want = water(sizes)
    assert all(abs(got[s] - want[s]) < 1e-6 * max(1, want[s]) for s in sizes)


@pytest.mark.parametrize("n", [1, 2, 3, 17, 1000])
def test_permutation(spark, n):
    rows = spark.range(n).select(M.permuted(F.col("id"), F.lit(n).cast("bigint"), F.lit(5).cast("bigint")).alias("p"))
    got = [r.p for r in rows.collect()]
    assert sorted(got) == list(range(n)) and (n < 17 or got != sorted(got))


def test_mix(spark):
    rows = [(i, " ".join(["w"] * (1 + i * 7919 % 300)), None if i % 9 == 0 else f"s{i % 4}") for i in range(800)]
    docs = spark.createDataFrame(rows, "doc_id bigint, text string, source string").repartition(7)
    got = M.mixed_documents(docs, block_words=32).collect()
    again = M.mixed_documents(docs.coalesce(1), block_words=32).collect()
    assert sorted(map(str, got)) == sorted(map(str, again))
    by: dict = {}
    for r in got:
        assert 0 <= r.taken <= 2 * r.size
        t = by.setdefault(r.source, [r.target, 0, r.source_size, 0])
        t[1] += r.taken
        t[3] += r.size
    assert all(abs(taken / target - 1) < 0.02 and size == total for target, taken, size, total in by.values())
    _, _, pieces = M.mixture(docs, block_words=32)
    per_slot = pieces.groupBy("rank", "shard", "n").agg(F.sum(F.col("word_to") - F.col("word_from")).alias("w"))
    assert per_slot.agg(F.max("w")).first()[0] == 32


def test_draws_are_multinomial_and_totals_are_the_quotas(spark):
    """Per shard the counts vary as a multinomial's; over all shards each source has its target to a block."""
    shares = {f"s{i:02d}": 20_000 * (1 + i % 3) for i in range(12)} | {"tiny": 900}
    sizes = spark.createDataFrame(list(shares.items()), "source string, source_size bigint")
    targets = M.source_targets(sizes).cache()
    want = {r["rank"]: r.target * -(-r.source_size // 10) / r.source_size for r in targets.collect()}
    slots = round(sum(want.values()))
    got = M.drawn_slots(targets, 10, slots, 256).groupBy("rank", "shard").agg(F.count("*").alias("n")).collect()
    total: dict = {}
    for r in got:
        total[r["rank"]] = total.get(r["rank"], 0) + r.n
    assert all(abs(total[k] - w) <= 1 for k, w in want.items()) and sum(total.values()) == slots
    shards = slots // 256
    by = {(r["rank"], r.shard): r.n for r in got}
    chi = []
    for k, w in want.items():
        p = w / slots
        chi += [(by.get((k, s), 0) - 256 * p) ** 2 / (256 * p * (1 - p)) for s in range(shards)]
    assert shards > 100 and 0.85 < sum(chi) / len(chi) < 1.15, sum(chi) / len(chi)


def test_words(spark):
    text = "a  b\tc\x0bd\x0ce\r\nf g 　 "
    assert M.measured(spark.createDataFrame([(1, text, "s")], "doc_id bigint, text string, source string")).first()["size"] == 7
