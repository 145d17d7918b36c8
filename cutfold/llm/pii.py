"""Personal data by bootstrapped contextual extraction.

Four kinds have a base rule each (email, ip, card, phone). Their matches are the
seeds of those kinds; a fifth kind, secret, has long hexadecimal keys as seeds. The
words around a span form lexical patterns: ``L`` (two words before), ``M`` (one word
before) and ``B`` (one on either side), with digits read as 0. Loose spans, of shapes
that no base rule takes (spelled-out or host-only addresses, defanged addresses,
numbers in groups, quoted or assigned values), have patterns too. All spans and
patterns make a graph that is scored in rounds over the whole corpus:

* an instance's score for a kind is 1 for a seed, else ``1 - prod(1 - 0.95 conf)``
  over its confident patterns;
* a pattern's confidence for a kind is ``pos / (pos + neg + 1)``: ``pos`` is the score
  of its distinct instances that count for the kind (seeds, and loose ones once they
  reach ``min_conf``), ``neg`` the number of distinct instances known to be something
  else: seeds of another kind, and numbers as long as a card that fail its check
  digit. Loose instances not yet decided count for neither, so a context full of
  unseen identifiers can become confident.

A pattern counts from ``min_seeds`` of ``pos`` on and from confidence ``min_conf``. A
loose span is reported under a kind when one of its patterns is confident of it. Its
instance then supports the other patterns it occurs in, which may have no seed at all.

Defined cases: NULL text is empty and has no span; repeated rows have equal spans,
and as instances are distinct strings, copies give a pattern no more support;
offsets are code points with exclusive ends. Context words are looked for within
``CONTEXT`` characters of a span and cut there, so a longer word is known by its
nearest part.
"""

from __future__ import annotations

import hashlib
import re

import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from cutfold.functions.storage import drop_saved, saved
from cutfold.llm._common import map_arrow

KINDS = ["email", "ip", "card", "phone"]
#: Further kinds are numbered after the base ones and reported apart from them.
SECRET = len(KINDS)
MIN_SEEDS, MIN_CONF, ROUNDS, CONTEXT = 5, 0.8, 4, 80

_LOCAL = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz0123456789._%+-")
# No match can start inside a run of digits, so runs are tried once.
_DOMAIN = re.compile(r"[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+")
_IP = re.compile(r"(?<![0-9])[0-9]++(?:\.[0-9]++){3}")
_CARD = re.compile(r"[0-9](?:[\x20-]?[0-9])+")
_PHONE = re.compile(r"\+[0-9][\x20().0-9-]+[0-9]")
_SPELLED = re.compile(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}(?: ?[\[(]at[\])] ?| at )[A-Za-z0-9-]{1,63}(?:(?:\.| ?[\[(]dot[\])] ?| dot )[A-Za-z0-9-]{1,63})+")
_HOST_ONLY = re.compile(r"(?<![A-Za-z0-9._%+-])[A-Za-z0-9._%+-]{1,64}@[A-Za-z0-9-]{1,63}(?![A-Za-z0-9.-])")
_DEFANGED = re.compile(r"(?<![A-Za-z0-9.])[0-9]{1,3}(?:(?:\[\.\]|\(\.\)| ?\[dot\] ?| dot |-|_)[0-9]{1,3}){3}(?![A-Za-z0-9_-])")
_NUMBER = re.compile(r"(?<![A-Za-z0-9+])\(?[0-9](?:[\x20()./_-]{0,2}[0-9])+(?![A-Za-z0-9])")
_HEX_KEY = re.compile(r"(?<![A-Za-z0-9])(?:[0-9a-f]{32}|[0-9a-f]{40}|[0-9a-f]{64})(?![A-Za-z0-9])")
_VALUE = re.compile(r"(?<=[=:\x20\"'])[A-Za-z0-9+/_-]{12,128}(?![A-Za-z0-9+/_.@-])")
_DIGIT = re.compile(r"[0-9]")


def _emails(text: str):
    last, at = 0, text.find("@")
    while at >= 0:
        start = at
        while start > last and text[start - 1] in _LOCAL:
            start -= 1
        m = _DOMAIN.match(text, at + 1) if start < at else None
        if m:
            yield start, m.end()
            last = m.end()
        at = text.find("@", max(at + 1, last))


def _luhn(digits: str) -> bool:
    total = 0
    for i, c in enumerate(reversed(digits)):
        n = int(c) * (1 + i % 2)
        total += n - 9 if n > 9 else n
    return total % 10 == 0


def _digits(s: str) -> str:
    return "".join(_DIGIT.findall(s))


def base_spans(text: str) -> list[tuple[int, int, int]]:
    """``(kind, start, end)`` of the base rules, by kind and start."""
    out = [(0, a, b) for a, b in _emails(text)]
    if not _DIGIT.search(text):
        return out
    for m in _IP.finditer(text):
        if all(len(p) <= 3 and int(p) <= 255 for p in (q.lstrip("0") or "0" for q in m.group().split("."))):
            out.append((1, *m.span()))
    for m in _CARD.finditer(text):
        d = _digits(m.group()) if m.end() - m.start() >= 13 else ""
        if 13 <= len(d) <= 19 and _luhn(d):
            out.append((2, *m.span()))
    for m in _PHONE.finditer(text):
        if 9 <= len(_digits(m.group())) <= 15:
            out.append((3, *m.span()))
    return out


def key_spans(text: str) -> list[tuple[int, int]]:
    """Long hexadecimal keys of letters and digits: the seeds of the kind secret."""
    return [m.span() for m in _HEX_KEY.finditer(text) if not m.group().isdigit() and _DIGIT.search(m.group())]


def loose_spans(text: str, taken: list[tuple[int, int, int]]) -> list[tuple[tuple[int, ...], bool, int, int]]:
    """``(possible kinds, ruled out, start, end)`` of spans outside the taken ones. What
    is ruled out has the length of its kind but fails its check."""
    out = []
    if " at " in text or "at]" in text or "at)" in text:
        out += [((0,), False, *m.span()) for m in _SPELLED.finditer(text)]
    if "@" in text:
        out += [((0,), False, *m.span()) for m in _HOST_ONLY.finditer(text)]
    if _DIGIT.search(text):
        for m in _DEFANGED.finditer(text):
            if all(int(p) <= 255 for p in re.findall(r"[0-9]+", m.group())):
                out.append(((1,), False, *m.span()))
        for m in _NUMBER.finditer(text):
            d = _digits(m.group())
            if 13 <= len(d) <= 19:
                out.append(((2,), not _luhn(d), *m.span()))
            elif 7 <= len(d) <= 15:
                out.append(((3,), False, *m.span()))
        for m in _VALUE.finditer(text):
            if _DIGIT.search(m.group()) and not m.group().isdigit():
                out.append(((SECRET,), False, *m.span()))
    spans = sorted((a, b) for _, a, b in taken)
    free, j, last = [], 0, 0
    for kinds, bad, a, b in sorted(out, key=lambda x: (x[2], -x[3])):
        while j < len(spans) and spans[j][1] <= a:
            j += 1
        # Of loose spans that overlap the first and longest stays.
        if a >= last and (j == len(spans) or spans[j][0] >= b):
            free.append((kinds, bad, a, b))
            last = b
    return free


def patterns_around(text: str, start: int, end: int) -> list[str]:
    """The lexical patterns of a span; digits in context words read as 0."""
    before = ["<s>", "<s>", *text[max(0, start - CONTEXT) : start].lower().split()][-2:]
    after = [*text[end : end + CONTEXT].lower().split(), "</s>"][:1]
    before, after = ([_DIGIT.sub("0", w) for w in ws] for ws in (before, after))
    return [f"L {before[0]} {before[1]}", f"M {before[1]}", f"B {before[1]} _ {after[0]}"]


def _render(spans) -> str:
    return ",".join(f"{KINDS[k]}:{a}:{b}" for k, a, b in spans)


_HIT = pa.struct([("kind", pa.int32()), ("kinds", pa.list_(pa.int32())), ("bad", pa.bool_()), ("start", pa.int32()), ("end", pa.int32()), ("instance", pa.string()), ("patterns", pa.list_(pa.string()))])
_ROW = "doc_id long, n_email long, n_ip long, n_card long, n_phone long, base_sha256 string, base array<struct<kind:int,start:int,end:int>>, hits array<struct<kind:int,kinds:array<int>,bad:boolean,start:int,end:int,instance:string,patterns:array<string>>>"


def _find(batch):
    counts, digest, base, hits = [[] for _ in KINDS], [], [], []
    for text in batch.column(1).to_pylist():
        text = text or ""
        spans = base_spans(text)
        for k in range(len(KINDS)):
            counts[k].append(sum(s[0] == k for s in spans))
        digest.append(hashlib.sha256(_render(spans).encode()).hexdigest())
        keys = [(SECRET, a, b) for a, b in key_spans(text) if not any(x < b and a < y for _, x, y in spans)]
        base.append([{"kind": k, "start": a, "end": b} for k, a, b in spans + keys])
        found = [(k, (k,), False, a, b) for k, a, b in spans + keys] + [(-1, *x) for x in loose_spans(text, spans + keys)]
        hits.append([{"kind": k, "kinds": list(ks), "bad": bad, "start": a, "end": b, "instance": text[a:b], "patterns": patterns_around(text, a, b)} for k, ks, bad, a, b in found])
    span = pa.struct([("kind", pa.int32()), ("start", pa.int32()), ("end", pa.int32())])
    cols = [batch.column(0), *(pa.array(c, pa.int64()) for c in counts), pa.array(digest, pa.string()), pa.array(base, pa.list_(span)), pa.array(hits, pa.list_(_HIT))]
    return pa.RecordBatch.from_arrays(cols, ["doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", "base", "hits"])


def score_patterns(edges: DataFrame, min_seeds: int = MIN_SEEDS, min_conf: float = MIN_CONF, rounds: int = ROUNDS) -> tuple[DataFrame, DataFrame]:
    """``edges(pattern, instance, kind, kinds, bad)``, distinct, kind -1 for loose spans
    -> confident ``(pattern, kind, conf)`` and ``(instance, kind, score)`` of the loose
    instances that reach ``min_conf``. Ends early when a round adds no instance."""
    known = edges.where("kind >= 0")
    # A bad instance speaks against each kind it looked like; a seed against all others.
    seeds = known.groupBy("pattern", "kind").agg(F.count_distinct("instance").cast("double").alias("n"))
    every = known.groupBy("pattern").agg(F.count_distinct("instance").cast("double").alias("all"))
    wrong = edges.where("kind < 0 and bad").select("pattern", "instance", F.explode("kinds").alias("kind"))
    wrong = wrong.groupBy("pattern", "kind").agg(F.count_distinct("instance").cast("double").alias("bad"))
    support = seeds.join(wrong, ["pattern", "kind"], "full_outer")
    support = saved(support.select("pattern", "kind", F.coalesce("n", F.lit(0.0)).alias("n"), F.coalesce("bad", F.lit(0.0)).alias("bad")), "pii-support")
    loose = saved(edges.where("kind < 0 and not bad").select("pattern", "instance", F.explode("kinds").alias("kind")).distinct(), "pii-loose")
    others = saved(every, "pii-others")
    told, sure, before = None, None, -1
    for _ in range(rounds):
        grown = support
        if told is not None:
            more = loose.join(told, ["instance", "kind"]).groupBy("pattern", "kind").agg(F.sum("score").alias("more"))
            grown = grown.join(more, ["pattern", "kind"], "full_outer").select("pattern", "kind", (F.coalesce("n", F.lit(0.0)) + F.coalesce("more", F.lit(0.0))).alias("pos"), F.coalesce("n", F.lit(0.0)).alias("n"), F.coalesce("bad", F.lit(0.0)).alias("bad"))
        else:
            grown = grown.withColumn("pos", F.col("n"))
        conf = grown.where(F.col("pos") >= min_seeds * (1 - 1e-9)).join(others, "pattern", "left")
        against = F.col("bad") + F.coalesce("all", F.lit(0.0)) - F.col("n")
        conf = conf.withColumn("conf", F.col("pos") / (F.col("pos") + against + 1))
        past = [t for t in (sure, told) if t is not None]
        sure = saved(conf.where(F.col("conf") >= min_conf).select("pattern", "kind", "conf"), "pii-confident")
        found = loose.join(sure, ["pattern", "kind"]).groupBy("instance", "kind").agg((1 - F.exp(F.sum(F.log1p(-0.95 * F.col("conf"))))).alias("score"))
        told = saved(found.where(F.col("score") >= min_conf * 0.95), "pii-scores")
        drop_saved(*past)
        count = told.count()
        if count == before:
            break
        before = count
    drop_saved(support, loose, others)
    return sure, told


def find_personal_data(docs: DataFrame, min_seeds: int = MIN_SEEDS, min_conf: float = MIN_CONF) -> DataFrame:
    """Per row ``doc_id``, base counts and digest, and ``found``: all spans as
    structs ``(kind, start, end)``, kinds numbered as in ``KINDS`` and by ``SECRET``."""
    src = docs.select(F.col("doc_id").cast("long").alias("doc_id"), "text")
    rows = saved(map_arrow(src, _find, _ROW).withColumn("rid", F.monotonically_increasing_id()), "pii-spans")
    hits = rows.select("rid", F.explode("hits").alias("h")).select("rid", "h.*").select("rid", "kind", "kinds", "bad", "start", "end", "instance", F.explode("patterns").alias("pattern"))
    edges = saved(hits.groupBy("pattern", "instance", "kind", "kinds", "bad").agg(F.lit(1).alias("one")).drop("one"), "pii-edges")
    sure, told = score_patterns(edges, min_seeds, min_conf)
    drop_saved(edges)
    spare = hits.where("kind < 0 and not bad").select("rid", "start", "end", "instance", "pattern", F.explode("kinds").alias("kind"))
    new = spare.join(sure.select("pattern", "kind"), ["pattern", "kind"]).join(told.select("instance", "kind"), ["instance", "kind"])
    new = new.groupBy("rid").agg(F.collect_set(F.struct(F.col("kind").cast("int").alias("kind"), "start", "end")).alias("more"))
    out = rows.drop("hits").join(new, "rid", "left")
    every = F.when(F.col("more").isNull(), F.col("base")).otherwise(F.array_sort(F.concat("base", "more")))
    return out.withColumn("found", every).drop("rid", "more", "base")


def op7_personal_data(spark, sf_dir):
    """The contract's columns, and ``n_found`` (spans of the four kinds), ``n_new`` (those
    of them that the method added), ``n_secret`` and ``secrets`` (``start:end``)."""
    out = find_personal_data(spark.read.parquet(f"{sf_dir}/documents.parquet"))
    names = F.array(*[F.lit(k) for k in KINDS])
    text = lambda s: F.concat_ws(":", F.get(names, s["kind"]), s["start"].cast("string"), s["end"].cast("string"))
    place = lambda s: F.concat_ws(":", s["start"].cast("string"), s["end"].cast("string"))
    own, secret = F.filter("found", lambda s: s["kind"] < SECRET), F.filter("found", lambda s: s["kind"] == SECRET)
    n = F.size(own).cast("long")
    base = F.col("n_email") + F.col("n_ip") + F.col("n_card") + F.col("n_phone")
    return out.select("doc_id", "n_email", "n_ip", "n_card", "n_phone", "base_sha256", F.array_join(F.transform(own, text), ",").alias("spans"), n.alias("n_found"), (n - base).alias("n_new"), F.size(secret).cast("long").alias("n_secret"), F.array_join(F.transform(secret, place), ",").alias("secrets"))
