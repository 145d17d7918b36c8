import hashlib
import re

import numpy as np
import pytest
import xxhash

from cutfold.llm import exact_dedup, line_dedup, simhash_dedup, substring_dedup

WORD = re.compile(r"[^\x20\x09-\x0D]+")
sha = lambda s: hashlib.sha256(s.encode()).hexdigest()
key = lambda r: (r[0] is None, r[0] or 0)


def test_exact_groups(docs, none, rows):
    norm = [re.sub(r"[\x20\x09-\x0D]", "", t or "") for _, t, _, _ in rows]
    got = exact_dedup.exact_groups(docs).collect()
    assert len(got) == len(rows)
    groups = {}
    for (i, t, _, _), n in zip(rows, norm):
        groups.setdefault(n, []).append((-len(t or ""), 2**63 if i is None else i, i))
    for r in got:
        members = groups[next(n for n in norm if sha(n) == r.text_sha256 and any(m[2] == r.doc_id for m in groups[n]))]
        assert r.group_size == len(members) and r.keep_id == min(members)[2]
    for n, members in groups.items():
        assert sum(r.kept for r in got if r.text_sha256 == sha(n)) == 1
    assert exact_dedup.exact_groups(none).count() == 0


def test_exact_dedup_keeps_columns(docs, none):
    out = exact_dedup.exact_dedup(docs)
    assert out.dtypes == docs.dtypes and out.count() == 10
    assert exact_dedup.exact_dedup(none).count() == 0


def test_radix_levels_past_the_head(spark):
    base = "x" * 40_000
    texts = [base + "a", base + "b", base + "a", "y" * 24, "y" * 24, "z" * 25, "z" * 24 + "w"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    keep = {r.doc_id: r.keep_id for r in exact_dedup.exact_groups(df).collect()}
    assert keep == {0: 0, 1: 1, 2: 0, 3: 3, 4: 3, 5: 5, 6: 6}


def test_lines(docs, none, rows):
    low = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    strip = lambda x: x.strip(" \t\n\x0b\x0c\r").translate(low)
    holders = {}
    for i, t, _, _ in rows:
        for line in (t or "").split("\n"):
            if len(strip(line)) >= 20:
                holders.setdefault(strip(line), set()).add(-1 if i is None else i)
    want = []
    for i, t, _, _ in rows:
        lines = (t or "").split("\n")
        kept = [x for x in lines if len(holders.get(strip(x), ())) < 3 or max(holders[strip(x)]) == i]
        want.append((i, len(lines), len(lines) - len(kept), "\n".join(kept)))
    got = [tuple(r) for r in line_dedup.dedup_lines(docs).collect()]
    assert sorted(got, key=repr) == sorted(want, key=repr)
    assert sum(x[2] for x in want) > 0
    assert line_dedup.dedup_lines(none).count() == 0


def test_small_filter_changes_nothing(docs):
    a = sorted(map(tuple, line_dedup.dedup_lines(docs, bits=2**20).collect()), key=repr)
    b = sorted(map(tuple, line_dedup.dedup_lines(docs).collect()), key=repr)
    assert a == b


def brute_repeats(rows, window=50):
    where = {}
    split = [(2**63 if i is None else i, WORD.findall(t or "")) for i, t, *_ in rows]
    for d, ws in split:
        for s in range(len(ws) - window + 1):
            k = tuple(ws[s : s + window])
            where[k] = min(where.get(k, d), d)
    out = []
    for (d, ws), (i, *_) in zip(split, rows):
        gone = np.zeros(len(ws), bool)
        for s in range(len(ws) - window + 1):
            if where[tuple(ws[s : s + window])] < d:
                gone[s : s + window] = True
        kept = [w for w, g in zip(ws, gone) if not g]
        out.append((i, len(ws), int(gone.sum()), " ".join(kept)))
    return sorted(out, key=repr)


def test_substrings(docs, none, rows):
    got = sorted(map(tuple, substring_dedup.remove_repeats(docs).collect()), key=repr)
    assert got == brute_repeats(rows)
    assert substring_dedup.remove_repeats(none).count() == 0


@pytest.mark.parametrize("seed", [1, 2])
def test_substrings_with_few_words(spark, seed):
    """Small vocabularies make runs and periods, where symbols are hardest to align."""
    rng = np.random.default_rng(seed)
    base = [" ".join(rng.choice(list("ab"), 150, p=[0.8, 0.2])), "a " * 200, "a b " * 90, " ".join(rng.choice(list("abcdefgh"), 300))]
    rows = []
    for i in range(24):
        a, b = rng.integers(len(base), size=2)
        x, y = base[a].split(), base[b].split()
        p, q = rng.integers(len(x)), rng.integers(len(y))
        rows.append((i, " ".join(x[p : p + 90] + list(rng.choice(list("abc"), int(rng.integers(4)))) + y[q : q + 120])))
    got = sorted(map(tuple, substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string")).collect()), key=repr)
    assert got == brute_repeats(rows)


def test_many_rows_without_an_id_share_a_passage(spark):
    rng = np.random.default_rng(5)
    passage = " ".join(f"p{i}" for i in range(55))
    filler = [f"f{i}" for i in range(5000)]
    rows = [(None, " ".join([*rng.choice(filler, int(rng.integers(1, 12))), passage, *rng.choice(filler, 3)])) for _ in range(15_000)]
    rows += [(7, "before " + passage + " after"), (7, passage), (9, passage + " x")]
    got = sorted(map(tuple, substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string").repartition(4)).collect()), key=repr)
    assert got == brute_repeats(rows)
    assert sum(r[2] == 55 for r in got) == 15_001


def test_a_longer_window(spark):
    words = [f"w{i}" for i in range(400)]
    rows = [(1, " ".join(words)), (2, "a b " + " ".join(words[30:330]) + " c"), (3, " ".join(words[:140]))]
    got = sorted(map(tuple, substring_dedup.remove_repeats(spark.createDataFrame(rows, "doc_id long, text string"), window=150).collect()), key=repr)
    assert got == brute_repeats(rows, 150)


def test_symbols_are_local():
    rng = np.random.default_rng(0)
    reach = substring_dedup.reach()
    core = rng.integers(0, 5, 300).astype(np.uint64)
    cuts = []
    for _ in range(4):
        pad = rng.integers(0, 5, int(rng.integers(5, 60))).astype(np.uint64)
        words = substring_dedup.mix(np.concatenate([pad, core, pad]), 1)
        start, _ = substring_dedup.recompress(words, np.zeros(len(words), int))
        s = start - len(pad)
        cuts.append(set(s[(s >= reach) & (s < 300 - reach)].tolist()))
    assert all(c == cuts[0] for c in cuts)


def test_simhash_components(docs, none, rows):
    def slow(t):
        ws = WORD.findall(re.sub("[A-Z]", lambda m: m[0].lower(), t or ""))
        if not ws:
            return 0
        grams = [" ".join(ws[i : i + 3]) for i in range(len(ws) - 2)] or [" ".join(ws)]
        h = [xxhash.xxh64_intdigest(g.encode(), 42) for g in grams]
        return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h))

    got = simhash_dedup.near_groups(simhash_dedup.fingerprints(docs)).collect()
    want = {(2**63 - 1 if i is None else i): slow(t) for i, t, _, _ in rows}
    assert {r._d: r.fp % 2**64 for r in got} == want and len(got) == len(rows)
    low = {d: min(e for e in want if bin(want[d] ^ want[e]).count("1") <= 2) for d in want}
    for r in got:
        assert r.component <= low[r._d]
    assert simhash_dedup.near_groups(simhash_dedup.fingerprints(none)).count() == 0
    kept = simhash_dedup.near_dedup(docs)
    assert kept.dtypes == docs.dtypes and kept.count() == len({r.component for r in got})


@pytest.mark.parametrize("bucket", [2, 256])
def test_pigeonhole_loses_no_link(spark, bucket):
    rng = np.random.default_rng(5)
    fps = rng.integers(-(2**62), 2**62, 120)
    near = [int(f) ^ (1 << int(rng.integers(62))) ^ (1 << int(rng.integers(62))) for f in fps for _ in range(3)]
    same_part = [int(x) & ~0x1FFFFF for x in rng.integers(0, 2**40, 60)]
    all_fp = sorted({*map(int, fps), *near, *same_part})
    df = spark.createDataFrame([(f, i) for i, f in enumerate(all_fp)], "fp long, d long")
    for parts in (2, 3):
        got = {(r.u, r.v) for r in simhash_dedup.links(df, 2, parts, bucket).collect()}
        want = {(i, j) for i in range(len(all_fp)) for j in range(i) if bin((all_fp[i] ^ all_fp[j]) % 2**64).count("1") <= 2}
        assert got == want


def test_threshold_allocation():
    cheap = {-1: 0.0, 0: 1.0, 1: 5.0, 2: 9.0}
    dear = {-1: 0.0, 0: 100.0, 1: 500.0, 2: 900.0}
    assert simhash_dedup.allocate(2, [cheap, dear, dear]) == [2, -1, -1]
    assert sum(simhash_dedup.allocate(2, [cheap, cheap])) == 1


def test_null_and_repeated_ids_join_no_groups(spark):
    texts = ["alpha beta gamma delta", "one two three four five", "red green blue white", "north east south west"]
    df = spark.createDataFrame(list(zip([None, None, 7, 7], texts)), "doc_id long, text string")
    got = simhash_dedup.near_groups(simhash_dedup.fingerprints(df)).collect()
    assert len({r.fp for r in got}) == len({r.root for r in got}) == 4
    assert sorted(r.component for r in got) == [7, 7, simhash_dedup.LAST, simhash_dedup.LAST]
    assert {r.text for r in simhash_dedup.near_dedup(df).collect()} == set(texts)
