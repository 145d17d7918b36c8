import corpus_pipeline
from cutfold.llm import pieces


def test_stages(spark, docs):
    cur = docs
    for name, stage in corpus_pipeline.STAGES[:-1]:
        out = stage(spark, cur, "")
        assert out.dtypes == cur.dtypes, name
        cur = out
    last = corpus_pipeline.STAGES[-1][1](spark, cur, "")
    assert last.count() == cur.count()
    text = {r.doc_id: r.text for r in cur.collect()}
    assert all(text[r.doc_id] == r.text for r in pieces.decode_documents(last).collect())


def test_run(spark):
    out = corpus_pipeline.run(spark, "/root/testdata/sf0.001")
    assert out.count() > 0 and {"doc_id", "ids", "n_pieces"} <= set(out.columns)
    assert len(corpus_pipeline.STAGES) == 5 and corpus_pipeline.ORACLE_SQL is None


def test_run_on_an_empty_table(spark, tmp_path):
    spark.read.parquet("/root/testdata/sf0.001/documents.parquet").limit(0).write.parquet(str(tmp_path / "documents.parquet"))
    assert corpus_pipeline.run(spark, str(tmp_path)).count() == 0


def test_near_stage_finds_all_near_copies(spark):
    import random

    rng = random.Random(3)
    rows, shingles = [], lambda t: {tuple(t.split()[i : i + 5]) for i in range(max(1, len(t.split()) - 4))}
    for base in range(8):
        words = [f"w{rng.randrange(900)}" for _ in range(120)]
        for copy in range(5):
            edited = list(words)
            for at in rng.sample(range(120), copy):
                edited[at] = f"x{rng.randrange(900)}"
            rows.append((len(rows), " ".join(edited)))
    rows += [(None, "an unrelated text without any id"), (None, "another one that shares no shingle")]
    root = list(range(len(rows)))
    for i, (_, a) in enumerate(rows):
        for j, (_, b) in enumerate(rows[:i]):
            x, y = shingles(a), shingles(b)
            if len(x & y) >= 0.8 * len(x | y):
                old, new = max(root[i], root[j]), min(root[i], root[j])
                root = [new if r == old else r for r in root]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    kept = corpus_pipeline.near_stage(spark, df, "").collect()
    assert sorted(r.text for r in kept) == sorted(rows[r][1] for r in set(root)) and len(kept) < len(rows) - 8


def test_full_meeting_rules_out_by_parity_what_cannot_be_similar(spark):
    import random

    import numpy as np

    from cutfold.llm import near_pairs
    from cutfold.llm.simhash_dedup import shingle_hashes

    rng = random.Random(5)
    base = [f"w{rng.randrange(900)}" for _ in range(100)]
    sets = []
    for _ in range(60):
        edited = list(base)
        for at in rng.sample(range(100), 2):
            edited[at] = f"x{rng.randrange(900)}"
        sets.append(np.unique(shingle_hashes(" ".join(edited), 5)))
    rows = [(0, 7, i, i, len(h), len(h), near_pairs.band_keys(h), near_pairs.parity(h)) for i, h in enumerate(sets)]
    left = spark.createDataFrame(rows, "band int, key long, id long, c long, n long, s long, keys array<long>, parity array<long>")
    met = {(r.u, r.v) for r in near_pairs._met(left, 0.8).select("u", "v").collect()}
    both = {(i, j): len(np.intersect1d(sets[i], sets[j])) for i in range(60) for j in range(i)}
    jaccard = {p: x / (len(sets[p[0]]) + len(sets[p[1]]) - x) for p, x in both.items()}
    assert {p for p, x in jaccard.items() if x >= 0.8} <= met
    # All 1770 pairs share the bucket and fit in size; most are near 0.65.
    assert len(met) < 300 and min(jaccard[p] for p in met) > 0.7
