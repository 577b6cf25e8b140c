"""The pipeline's near-duplicate stage against brute-force Jaccard similarity of whole texts."""

import random

import pytest

import corpus_pipeline as pipeline
from weftgraph.llm import graphs, nearcopies

SMALL = "/root/testdata/sf0.01"


def brute_shingles(text: str, words: int = 5) -> frozenset:
    own = text.encode().lower().split()
    return frozenset(tuple(own[i : i + words]) for i in range(max(1, len(own) - words + 1))) if own else frozenset()


def brute_components(rows: list[tuple[int, str]], percent: int = 80) -> dict[int, int]:
    sets = [(d, brute_shingles(t)) for d, t in rows]
    root = {d: d for d, _ in rows}
    for i, (a, x) in enumerate(sets):
        for b, y in sets[i + 1 :]:
            if x == y or (min(len(x), len(y)) * 100 >= max(len(x), len(y)) * percent and len(x & y) * 100 >= len(x | y) * percent):
                old, new = max(root[a], root[b]), min(root[a], root[b])
                root = {k: new if v == old else v for k, v in root.items()}
    return root


def test_stage_drops_near_copies(spark):
    docs = spark.read.parquet(f"{SMALL}/documents.parquet")
    rows = [(r.doc_id, r.text) for r in docs.select("doc_id", "text").collect()]
    true = set(brute_components(rows).values())
    assert len(true) < len({brute_shingles(t) for _, t in rows})  # there are near copies that are not equal
    kept = pipeline.one_of_near_copies(spark, docs, SMALL)
    assert sorted(r.doc_id for r in kept.select("doc_id").collect()) == sorted(true)


@pytest.mark.parametrize("rounds", [1, 3])
def test_chains_long_lists_and_blanks(spark, rounds):
    """Texts that drift word by word: neighbours are near copies, the ends are not."""
    rng = random.Random(5)
    rows, words = [], [f"w{rng.randrange(10**6)}" for _ in range(60)]
    for i in range(60):
        rows.append((i + 1, " ".join(words)))
        words = [*words]
        words[rng.randrange(60)] = f"w{rng.randrange(10**6)}"
    common = " ".join(f"c{i}" for i in range(12))
    rows += [(100 + i, f"{common} " + " ".join(f"u{i}x{j}" for j in range(6))) for i in range(30)]
    base = [f"t{i}" for i in range(40)]  # one template, each copy changed at a place of its own, some twice alike
    for i in range(25):
        copy = [*base]
        copy[3 + i % 35] = f"v{i // 2 if i % 5 == 0 else i}"
        rows += [(300 + i, " ".join(copy)), *([(400 + i, " ".join([*copy, "end"]))] if i % 8 == 0 else [])]
    rows += [(200, ""), (201, "  "), (202, "One two"), (203, "one TWO"), (204, "two one"), (205, "one")]
    got = nearcopies.near_copies(spark.createDataFrame(rows, "doc_id long, text string"), rounds=rounds)
    assert {r.doc_id: r.component_id for r in got.collect()} == brute_components(rows)


def test_one_id_over_different_texts(spark):
    texts = [" ".join(f"w{i}x{j}" for j in range(30)) for i in range(4)]
    docs = spark.createDataFrame([(1, texts[0]), (1, texts[1]), (1, texts[1]), (2, texts[2]), (None, texts[3])], "doc_id long, text string")
    assert sorted(r.text for r in pipeline.one_of_near_copies(spark, docs, SMALL).collect()) == texts


def test_large_group_is_not_compared_pair_by_pair(spark, monkeypatch):
    """Copies of one template around the threshold: what is compared stays near the number of copies."""
    rng, base, rows = random.Random(9), [f"t{i}" for i in range(60)], []
    for i in range(300):
        copy = [*base]
        for at in rng.sample(range(60), rng.randint(1, 4)):
            copy[at] = f"v{i}x{at}"
        rows.append((i + 1, " ".join(copy)))
    asked = []

    def counted(f):
        def run(pairs, *rest):
            asked.append(pairs.count())
            return f(pairs, *rest)

        return run

    for name in ("_similar", "_alike"):
        if hasattr(nearcopies, name):
            monkeypatch.setattr(nearcopies, name, counted(getattr(nearcopies, name)))
    got = nearcopies.near_copies(spark.createDataFrame(rows, "doc_id long, text string"))
    assert {r.doc_id: r.component_id for r in got.collect()} == brute_components(rows)
    assert sum(asked) < 12 * len(rows) < len(rows) ** 2 / 4


def test_small_tables_take_few_tasks(spark):
    """With many partitions, what is done for a small group of near copies is not spread over all of them in every step."""
    rng, base = random.Random(3), [f"t{i}" for i in range(60)]
    rows = [(i + 1, " ".join(w if rng.random() < 0.96 else f"v{i}x{at}" for at, w in enumerate(base))) for i in range(60)]
    sc, old = spark.sparkContext, {k: spark.conf.get(k) for k in ("spark.sql.shuffle.partitions", "spark.sql.adaptive.coalescePartitions.enabled")}
    try:
        for k, v in zip(old, ("24", "false"), strict=True):
            spark.conf.set(k, v)
        sc.setJobGroup("few-tasks", "")
        got = {r.doc_id: r.component_id for r in nearcopies.near_copies(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
        jobs = [sc.statusTracker().getJobInfo(j) for j in sc.statusTracker().getJobIdsForGroup("few-tasks")]
        stages = [sc.statusTracker().getStageInfo(s) for j in jobs for s in j.stageIds]
    finally:
        sc.setLocalProperty("spark.jobGroup.id", None)
        for k, v in old.items():
            spark.conf.set(k, v)
    assert got == brute_components(rows)
    assert 0 < sum(s.numCompletedTasks for s in stages if s) < 2400


def test_components_on_the_driver_and_apart(spark):
    rng = random.Random(8)
    links = [(rng.randrange(-400, 400), rng.randrange(-400, 400)) for _ in range(350)] + [(i, i + 1) for i in range(10**6, 10**6 + 40)] + [(None, 3), (4, 4)]
    df = spark.createDataFrame(links, "a long, b long")
    apart, here = ({r.node: r.component for r in graphs.components(df, gathered=n).collect()} for n in (0, 1000))
    assert here == apart and len(set(here.values())) < len(here)
    assert {r.node: r.component for r in graphs.components(df, gathered=10).collect()} == here  # too many: not on the driver
    assert graphs.components(df.where("a = b"), gathered=1000).count() == 0
