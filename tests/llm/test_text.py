import hashlib
import random
import re
import struct

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

from cutfold.llm import mixing, pieces, pii, sketches


@pytest.fixture(scope="module")
def vocabulary():
    return pieces.Vocabulary()


def test_round_trip(docs, none, rows):
    enc = pieces.encode_documents(docs, keep=("doc_id", "source"))
    assert enc.columns == ["doc_id", "source", "n_pieces", "ids"]
    dec = pieces.decode_documents(enc).collect()
    assert sorted((r.text for r in dec)) == sorted(t or "" for _, t, _, _ in rows)
    told = pieces.encode_documents(docs, emit_ids=False).collect()
    assert all(r.round_trip for r in told) and len(told) == len(rows)
    assert pieces.encode_documents(none).count() == 0


def brute(v, text):
    """Best score by a plain dynamic programme over characters."""
    names = {s.decode(): i for i, s in enumerate(v.surface) if not v.is_byte[i] and s and v.score[i]}
    best = [0.0] + [-1e18] * len(text)
    for e in range(1, len(text) + 1):
        for s in range(max(0, e - v.longest), e):
            p = names.get(text[s:e])
            gain = v.score[p] if p is not None else v.unknown if e - s == 1 else None
            if gain is not None:
                best[e] = max(best[e], best[s] + gain)
    return best[-1]


def test_viterbi_is_best(vocabulary):
    rng = random.Random(3)
    words = ["hello", "unbelievable", "x", "ünï", "你好", "🦕", "a-b", "12,345", "    ", "ththe"]
    texts = [" ".join(rng.choice(words) for _ in range(rng.randint(1, 8))) for _ in range(60)]
    ids, per = pieces.Encoder(vocabulary).encode(texts)
    for text, a, b in zip(texts, np.cumsum(per) - per, np.cumsum(per)):
        own, score, i = ids[a:b], 0.0, 0
        while i < len(own):
            if vocabulary.is_byte[own[i]]:
                first = vocabulary.surface[own[i]][0]
                i += 1 if first < 0x80 else 2 if first < 0xE0 else 3 if first < 0xF0 else 4
                score += vocabulary.unknown
            else:
                score += vocabulary.score[own[i]]
                i += 1
        assert score == pytest.approx(brute(vocabulary, " " + text))


def test_library_agrees(vocabulary):
    model = pytest.importorskip("sentencepiece.sentencepiece_model_pb2")
    import sentencepiece

    m = model.ModelProto()
    m.ParseFromString(open(pieces.MODEL, "rb").read())
    m.trainer_spec.model_type = 1
    for i, p in enumerate(m.pieces):
        if p.type == 1:
            p.score = float(vocabulary.score[i])
    sp = sentencepiece.SentencePieceProcessor(model_proto=m.SerializeToString())
    texts = ["Hello  world, this is a test\nwith lines", "Grüße aus Köln 🦕", "", " lead and trail "]
    ids, per = pieces.Encoder(vocabulary).encode(texts)
    ends = np.cumsum(per)
    for t, a, b in zip(texts, ends - per, ends):
        assert ids[a:b].tolist() == sp.encode(t)


def test_double_array_holds_its_keys():
    keys = [(1,), (1, 2), (1, 2, 3), (2, 1), (3, 3, 3, 3), (500, 1), (500, 499)]
    t = pieces.DoubleArray(keys, list(range(len(keys))))

    def find(key):
        s = 0
        for c in key:
            n = t.base[s] + c
            if n >= len(t.check) or t.check[n] != s:
                return -1
            s = n
        return t.value[s]

    assert [find(k) for k in keys] == list(range(len(keys)))
    assert find((3, 3)) == -1 and find((9,)) == -1 and find((1, 3)) == -1


def test_mix_targets(spark):
    rows = [(i, "w " * 10, f"s{i % 5}", ) for i in range(500)]
    units = [(i, i, s, 10) for i, _, s in rows] + [(900, 1, None, 0), (901, 1, None, 40)]
    units = spark.createDataFrame([(i, *u) for i, u in enumerate(units)], "rid long, id long, h long, source string, size long")
    goals = {r.source: r for r in mixing.source_targets(units).collect()}
    weight = {"s0": 5, "s1": 2, "s2": 1, "s3": 5, "s4": 2, None: 1}
    size = {s: goals[s].source_size for s in goals}
    target, free, left = {}, set(size), sum(size.values())
    while free:
        unit = left / sum(weight[s] for s in free)
        over = {s for s in free if unit * weight[s] > 3 * size[s]}
        if not over:
            target |= {s: unit * weight[s] for s in free}
            break
        for s in over:
            target[s] = 3.0 * size[s]
            left -= target[s]
        free -= over
    for s in goals:
        assert goals[s].target == pytest.approx(target[s])
    out = mixing.mix_copies(units)
    got = {r.source: r for r in out.groupBy("source").agg(F.sum(F.col("size") * F.col("copies")).alias("t"), F.max("copies").alias("c"), F.max("target").alias("g")).collect()}
    for s, r in got.items():
        assert abs(r.t - r.g) <= 40 and r.c <= 3
    again = {(r.id, r.copies) for r in mixing.mix_copies(units.repartition(3)).collect()}
    assert again == {(r.id, r.copies) for r in out.collect()}


def test_mix_is_unbiased(spark):
    """Over many sources of equal make-up each row is taken as often as it should."""
    rows = [(i, i, i * 31, f"s{i // 10:03d}", 5 + 7 * (i % 10)) for i in range(3000)]
    out = mixing.mix_copies(spark.createDataFrame(rows, "rid long, id long, h long, source string, size long"), weights=(1, 2))
    r = out.withColumn("p", F.col("target") / F.col("source_size")).groupBy("size").agg(F.avg(F.col("copies") - F.col("p")).alias("d")).collect()
    assert all(abs(x.d) < 0.12 for x in r)


def test_mix_edges(docs, none, rows):
    out = mixing.mix_documents(docs)
    assert out.dtypes == docs.dtypes
    assert mixing.mix_documents(none).count() == 0
    assert out.where("text is null or doc_id in (4, 5)").count() == 0


@pytest.mark.parametrize("repeats", [10, 3])
def test_mix_of_repeated_rows(spark, repeats):
    """Every row several times, over several partitions: the sources still meet their
    targets within one document, and copies of a row differ by one at most."""
    rows = [(i, "w " * (1 + i * 7 % 90), "abc"[i % 3]) for i in range(400)] * repeats
    rows += [(9000, "same words in all of these rows", "c")] * 700 + [(None, "no id", None)] * 40
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    copies = mixing.mix_copies(mixing._units(df, F.monotonically_increasing_id())).collect()
    assert len(copies) == len(rows) and len({r.rid for r in copies}) == len(rows)
    for s in ("a", "b", "c", None):
        mine = [r for r in copies if r.source == s]
        assert abs(sum(r.size * r.copies for r in mine) - mine[0].target) < max(r.size for r in mine)
    for same in {(r.id, r.h) for r in copies}:
        got = {r.copies for r in copies if (r.id, r.h) == same}
        assert max(got) - min(got) <= 1 and max(got) <= 3
    again = mixing.mix_copies(mixing._units(df.repartition(2), F.monotonically_increasing_id())).groupBy("id", "h").agg(F.sum("copies")).collect()
    total = {}
    for r in copies:
        total[r.id, r.h] = total.get((r.id, r.h), 0) + r.copies
    assert {(r[0], r[1]): r[2] for r in again} == total


def slow_spans(t):
    out = [("email", *x.span()) for x in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
    out += [("ip", *x.span()) for x in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) <= 255 for p in x.group().split("."))]
    for x in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
        d = re.sub("[^0-9]", "", x.group())
        if 13 <= len(d) <= 19 and sum(sum(divmod(int(c) * (1 + i % 2), 10)) for i, c in enumerate(d[::-1])) % 10 == 0:
            out.append(("card", *x.span()))
    out += [("phone", *x.span()) for x in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 9 <= len(re.sub("[^0-9]", "", x.group())) <= 15]
    return out


def test_base_spans():
    rng = random.Random(1)
    for _ in range(8000):
        t = "".join(rng.choice("a1 @.-+2(3)%9é") for _ in range(rng.randint(0, 40)))
        assert [(pii.KINDS[k], a, b) for k, a, b in pii.base_spans(t)] == slow_spans(t)
    assert pii.base_spans("1" * 200_000) == [] and pii.base_spans("a" * 200_000) == []


def test_patterns_discover(spark):
    rows = [(i, f"please call me at +1 (555) 555-{1000 + i} today") for i in range(8)]
    rows += [(20, "please call me at 555 123 4567 today"), (21, "we had 555 123 4567 cows"), (22, None), (23, "")]
    rows += [(30 + i, f"write to user{i} at host{i} dot example dot com or") for i in range(3)]
    got = {r.doc_id: [tuple(x) for x in r.found] for r in pii.find_personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[20] == [(3, 18, 30)] and got[21] == [] and got[22] == [] and got[23] == [] and got[30] == []
    assert got[0] == [(3, 18, 35)]


def test_patterns_discover_in_a_planted_corpus(spark):
    """Identifiers that no base rule takes, in contexts shared with seeds, in a context
    that only discovered ones share, and decoys in contexts of their own."""
    rng = random.Random(4)
    word = lambda: f"w{rng.choice('abcdefgh')}{rng.choice('klmnop')}"
    noise = lambda n: " ".join(word() for _ in range(n))
    local = [f"0{rng.randint(20, 99)} {rng.randint(1000, 9999)} {rng.randint(100, 999)}" for _ in range(60)]
    rows, planted, decoys = [], set(), set()

    def put(before, span, after="", wanted=None):
        start = noise(6) + before
        rows.append((len(rows), start + span + after + noise(5)))
        place = (len(rows) - 1, len(start), len(start) + len(span))
        if wanted is not None:
            (planted if wanted else decoys).add(place)

    for i in range(12):
        put(" you can phone me: ", f"+49 30 {rng.randint(1000000, 9999999)}", " ")
        put(" mail goes to ", f"user{i}@mail.example.org", " ")
        put(" from host ", f"10.1.{i}.{rng.randint(0, 255)}", " ")
    for n in local[:30]:
        put(" you can phone me: ", n, " ", True)
    for n in local[:30]:  # the same numbers where no seed ever stands
        put(" reachable under ", n, " ", True)
    for n in local[30:45]:  # other numbers there: found through the second context only
        put(" reachable under ", n, " ", True)
    for i in range(10):
        put(" mail goes to ", f"jane{i} at home{i} dot example", " ", True)
        put(" from host ", f"10[.]2[.]{i}[.]7", " ", True)
    for n in local[45:]:
        put(" crates in stock ", n, " ", False)
    for i in range(20):
        put(" the gap is ", f"{rng.randint(10**15, 10**16 - 1)}", " ")
    df = spark.createDataFrame(rows, "doc_id long, text string")
    found = {(r.doc_id, s.start, s.end) for r in pii.find_personal_data(df).collect() for s in r.found}
    base = {(d, a, b) for d, t in rows for _, a, b in pii.base_spans(t)}
    new = found - base
    assert base <= found and not new & decoys
    assert len(new & planted) / len(new) >= 0.95 and len(new & planted) / len(planted) >= 0.95


def test_secrets_by_context(spark):
    key = lambda i: hashlib.sha1(str(i).encode()).hexdigest()
    rows = [(i, f'some words token = "{key(i)}" and more') for i in range(8)]
    rows += [(20, 'some words token = "Zk3x-99Abcd_efgh77" and more'), (21, "an order Zk3x-99Abcd_efgh78 of things"), (22, "words " + key(1)[:32])]
    got = {r.doc_id: [tuple(x) for x in r.found] for r in pii.find_personal_data(spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got[0] == [(4, 20, 60)] and got[20] == [(4, 20, 38)] and got[21] == [] and got[22] == [(4, 6, 38)]


def test_pii_edges(docs, none, rows):
    out = pii.find_personal_data(docs).collect()
    assert len(out) == len(rows)
    mail = next(r for r in out if r.doc_id == 12)
    assert (mail.n_email, mail.n_ip, mail.n_card, mail.n_phone) == (1, 1, 1, 1)
    assert pii.find_personal_data(none).count() == 0


def h64(*v):
    s = 42
    for x in v:
        s = xxhash.xxh64_intdigest(x if isinstance(x, bytes) else struct.pack("<q", x), s)
    return s - 2**64 if s >= 2**63 else s


def slow_sketch(t, k=64):
    w = [h64(x) for x in (t or "").encode().split()]
    if not w:
        return []
    return sorted({h64(*w[i : i + 5]) for i in range(len(w) - 4)} if len(w) >= 5 else {h64(*w)})[:k]


def test_fingerprints(docs, none, rows):
    text = {(-(2**63) if i is None else i): t or "" for i, t, _, _ in rows}
    ids = sorted(text, reverse=True)
    out = sketches.fingerprint_edits(docs).collect()
    assert len(out) == len(rows)
    for r in out:
        d = -(2**63) if r.doc_id is None else r.doc_id
        t, nxt = text[d], text[ids[(ids.index(d) + 1) % len(ids)]]
        edited = t[: len(t) - len(t) // 3] + nxt[: len(t) // 3]
        assert r.n_chars == len(t) and r.edited_sha256 == hashlib.sha256(edited.encode()).hexdigest()
        a, b, c = slow_sketch(t), slow_sketch(edited), slow_sketch(nxt)
        assert r.sketch == a and r.edited_sketch == b
        for other, got in ((b, r.near_edited), (c, r.near_next)):
            u = sorted(set(a) | set(other))[:64]
            assert got == pytest.approx(len(set(u) & set(a) & set(other)) / len(u) if u else 1.0)
    assert sketches.fingerprint_edits(none).count() == 0


def test_sketches_merge(spark):
    rows = [("g" if i % 3 else "h", " ".join(f"w{j}" for j in range(i, i + 30))) for i in range(600)]
    df = spark.createDataFrame(rows, "g string, text string")
    merged = {r.g: r.sketch for r in sketches.merge_groups(sketches.sketch_documents(df, F.col("g")), "g", fan_in=16).collect()}
    for g in "gh":
        every = sorted({x for q, t in rows if q == g for x in slow_sketch(t, 10**6)})
        assert merged[g] == every[:64]
    est = spark.createDataFrame([(merged["g"],)], "s array<bigint>").select(sketches.distinct_shingles(F.col("s"))).first()[0]
    true = len({x for q, t in rows if q == "g" for x in slow_sketch(t, 10**6)})
    assert 0.6 * true < est < 1.6 * true


def test_containment(spark):
    small = slow_sketch(" ".join(f"w{i}" for i in range(200)), 512)
    large = slow_sketch(" ".join(f"w{i}" for i in range(2000)), 512)
    df = spark.createDataFrame([(small, large)], "a array<bigint>, b array<bigint>")
    c, r = df.select(sketches.containment(F.col("a"), F.col("b"), 512), sketches.resemblance(F.col("a"), F.col("b"), 512)).first()
    assert c > 0.9 and 0.05 < r < 0.2


@pytest.mark.parametrize("span", ["jane.doe at example.com", "jane at example[dot]com", "jane at example (dot) com", "jane[at]example.com", "jane (at) example dot com"])
def test_every_spelling_of_an_address_is_a_loose_span(span):
    assert pii.loose_spans(f"Write to {span}", []) == [((0,), False, 9, 9 + len(span))]
