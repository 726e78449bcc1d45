"""Operators against brute force on small fixtures: nulls, empties, ties, repeats, long texts, clashing columns."""

from __future__ import annotations

import collections
import hashlib
import math
import random
import re
import zlib

import numpy as np
import pytest
import xxhash
from pyspark.sql import functions as F

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
rng = random.Random(8)
WORDS = ["the", "of", "Rain", "rain", "stone.", "é", "日本", "x1", "über", "walk,", "a", "river", "green", "lamp"]


def prose(n, seed=0):
    r = random.Random(seed)
    return " ".join(r.choice(WORDS) for _ in range(n))


def make(spark, texts, first=0):
    return spark.createDataFrame([(first + i, t, "en", f"s{i % 3}", len(t or "")) for i, t in enumerate(texts)], DOCS)


EDGE = [None, "", " \n\t ", "a", "A  a b", prose(3000, 1), prose(40, 2), prose(40, 2), prose(40, 2).replace(" ", "  "), "😀 \U00020000 ß"]


CLASH = ("score", "predicted", "_text", "_t", "_id", "_mask", "_done", "t", "b", "base", "mask", "key", "row", "words", "digest", "w_digest", "rid", "fp", "f0", "id", "u", "h", "n", "shard", "cluster", "copy", "first", "held_out")


@pytest.fixture(scope="module")
def edge(spark):
    # columns whose names clash with those that operators add
    return make(spark, EDGE).withColumns({c: F.lit("x") for c in CLASH}).persist()


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


# ---- 6


@pytest.mark.parametrize("weak", [False, True])
def test_exact_dedup(spark, edge, weak):
    from quiesce.llm.exact_dedup import exact_dedup

    df = exact_dedup(edge, digest=lambda t: F.substring(F.sha2(t.cast("binary"), 256), 1, 1), strong=False) if weak else exact_dedup(edge)
    groups = collections.defaultdict(list)
    norm = {i: re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for i, t in enumerate(EDGE)}
    for i, t in norm.items():
        groups[t].append(i)
    got = {r.doc_id: r for r in df.collect()}
    assert len(got) == len(EDGE)
    for i, t in norm.items():
        assert (got[i].keep_id, got[i].group_size, got[i].kept) == (min(groups[t]), len(groups[t]), i == min(groups[t]))
        if not weak:
            assert got[i].digest == hashlib.sha256(t.encode()).hexdigest()


def test_exact_dedup_hot_group_and_repeats(spark, empty):
    from quiesce.llm.exact_dedup import exact_dedup

    rows = make(spark, ["same text"] * 300 + [f"t{i}" for i in range(50)]).repartition(9)
    got = exact_dedup(rows.unionAll(rows.filter("doc_id = 0"))).collect()
    assert len(got) == 351 and sum(r.group_size == 301 for r in got) == 301
    assert exact_dedup(empty).count() == 0


# ---- 9


def slow_print(text):
    w = (text or "").encode().lower().split()
    if not w:
        return 0
    hs = [xxhash.xxh64_intdigest(b" ".join(w[i : i + 4]), 42) for i in range(max(1, len(w) - 3))]
    return sum(1 << k for k in range(64) if 2 * sum(h >> k & 1 for h in hs) > len(hs))


def slow_components(prints, radius=4):
    ids = list(prints)
    up = {i: i for i in ids}

    def root(i):
        while up[i] != i:
            i = up[i]
        return i

    for a in range(len(ids)):
        for b in range(a):
            if (prints[ids[a]] ^ prints[ids[b]]).bit_count() <= radius:
                x, y = root(ids[a]), root(ids[b])
                up[max(x, y)] = min(x, y)
    return {i: root(i) for i in ids}


def test_simhash(spark, edge, empty):
    from quiesce.llm.simhash import near_duplicates

    base = prose(400, 3).split()
    texts = list(EDGE)
    for k in range(30):
        words = list(base)
        for _ in range(k % 4):
            words[random.Random(k).randrange(len(words))] = f"w{k}"
        texts.append(" ".join(words))
    want_fp = {i: slow_print(t) for i, t in enumerate(texts)}
    want = slow_components(want_fp)
    for hot in (20_000, 3):
        docs = make(spark, texts).withColumns({c: F.lit("x") for c in CLASH})
        got = {r.doc_id: r for r in near_duplicates(docs, hot=hot).collect()}
        assert {i: int(r.fingerprint, 16) for i, r in got.items()} == want_fp
        assert {i: r.component_id for i, r in got.items()} == want
    assert near_duplicates(empty).count() == 0
    odd = near_duplicates(make(spark, ["one two", "one two", "three"]).withColumn("doc_id", F.when(F.col("doc_id") == 0, 7)).unionByName(make(spark, ["one two"], 7))).collect()
    assert sorted((r.doc_id, r.component_id) for r in odd if r.doc_id) == [(7, 7), (7, 7)] and sum(r.component_id is None for r in odd) == 1


def test_simhash_finds_copies_alike_to_four_fifths(spark):
    """Every pair of five-word similarity 0.8 or more among texts of a few hundred words, against the sets themselves."""
    import corpus_pipeline
    from quiesce.llm.simhash import near_duplicates

    r = random.Random(3)
    vocabulary = [f"w{i}" for i in range(4000)]
    texts = []
    for _ in range(25):
        words = [r.choice(vocabulary) for _ in range(300)]
        texts.append(" ".join(words))
        copy = list(words)
        for at in r.sample(range(0, 290, 6), r.randrange(1, 6)):
            copy[at] = "changed"
        texts.append(" ".join(copy))
    sets = [{tuple(t.split()[i : i + 5]) for i in range(len(t.split()) - 4)} for t in texts]
    got = {x.doc_id: x.component_id for x in near_duplicates(make(spark, texts), **corpus_pipeline.NEAR).collect()}
    for a in range(len(texts)):
        for b in range(a):
            alike = len(sets[a] & sets[b]) / len(sets[a] | sets[b])
            assert alike < 0.8 or got[a] == got[b]
            assert alike > 0.5 or got[a] != got[b]


def test_links_lose_nothing_on_chains(spark):
    from quiesce.llm.simhash import components, links

    r = random.Random(1)
    fps, x = set(), r.getrandbits(64)
    for _ in range(300):  # a long chain with steps of at most four bits
        for _ in range(r.randrange(1, 5)):
            x ^= 1 << r.randrange(64)
        fps.add(x)
    fps |= {r.getrandbits(64) for _ in range(300)}
    want = slow_components({f: f for f in sorted(fps)})
    signed = lambda v: v - (1 << 64) if v >> 63 else v
    # the fingerprints are their own ids
    df = spark.createDataFrame([(signed(f), signed(f)) for f in fps], "id long, f0 long")
    got = {r.node: r.root for r in components(links(df)).collect()}
    groups = collections.defaultdict(set)
    for f, c in want.items():
        groups[c].add(signed(f))
    for members in groups.values():
        assert {got.get(m, m) for m in members} == {min(members)}


# ---- 7


def test_bpe_equals_the_library(spark, edge):
    import public_tokenizers as P
    import tiktoken

    from quiesce.llm import bpe

    path = P.path("byte_bpe_multi_50k.tiktoken")
    ranks = bpe.read_ranks(path)
    own = tiktoken.Encoding("own", pat_str=P.PATTERN, mergeable_ranks=ranks, special_tokens={})
    got = {r.doc_id: r for r in bpe.digests(edge, path, P.PATTERN).collect()}
    for i, t in enumerate(EDGE):
        ids = own.encode_ordinary(t or "")
        assert got[i].n_tokens == len(ids)
        assert got[i].ids_sha256 == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got[i].decoded_sha256 == hashlib.sha256((t or "").encode()).hexdigest()
    coder = bpe.load(path, P.PATTERN)
    for seed in range(300):
        r = random.Random(seed)
        t = "".join(r.choice("aeiotnsr éñßä.,!? \n01日本") for _ in range(200))
        assert np.frombuffer(coder.encode(t), "<u4").tolist() == own.encode_ordinary(t)
    for t in ("a" * 2000, "ab" * 1500, "!" * 999):
        assert np.frombuffer(coder.encode(t), "<u4").tolist() == own.encode_ordinary(t)
    back = bpe.decode(bpe.encode(edge, path, P.PATTERN), path, P.PATTERN).collect()
    assert all(bytes(r.content) == (EDGE[r.doc_id] or "").encode() for r in back)


# ---- 8


def slow_tree(texts, train, depth, least, test):
    """Probability of a word after a context, straight from the definition."""
    count = [collections.Counter(tuple(t[i - d : i + 1]) for t, ok in zip(texts, train) if ok for i in range(d, len(t))) for d in range(depth + 1)]
    after = collections.defaultdict(dict)
    for d in range(1, depth + 1):
        for k, n in count[d].items():
            if n >= 2:
                after[k[:-1]][k[-1]] = n
    n, v, memo = sum(count[0].values()), len(count[0]), {}

    def inside(ctx):
        if ctx not in memo:
            c, told = count[len(ctx) - 1][ctx], after.get(ctx, {})
            memo[ctx] = not ctx or (inside(ctx[1:]) and c >= least and len(told) > 0 and sum(x * math.log(x / c / p(ctx[1:], w)) for w, x in told.items()) > test * len(told))
        return memo[ctx]

    def p(ctx, w):
        if not ctx:
            return (count[0][(w,)] + 1) / (n + v + 1)
        if not inside(ctx):
            return p(ctx[1:], w)
        c, told = count[len(ctx) - 1][ctx], after[ctx]
        rest = c - sum(told.values()) + 0.75 * len(told)
        return (max(told.get(w, 0) - 0.75, 0) + rest * p(ctx[1:], w)) / c

    return p, count[0], n, v, memo


def test_suffix_tree(spark, empty):
    from quiesce.llm.suffix_tree import score_texts

    phrases = [f"a{i} b{i % 4} c{i} the d{i % 3}" for i in range(9)]
    texts = EDGE + [" ".join(rng.choice(phrases) for _ in range(12)) for _ in range(40)] + [prose(5000, 99)]
    docs = make(spark, texts).unionByName(make(spark, [texts[12]], 12)).withColumns({c: F.lit("x") for c in ("block", "held", "words", "score", "_text")})
    rows = score_texts(docs, depth=3, block_bytes=900).collect()
    got = {r.doc_id: r for r in rows}
    assert len(rows) == len(texts) + 1 and len({r.score for r in rows if r.doc_id == 12}) == 1  # a repeated row counts and is scored twice
    tokens = [(t or "").encode().lower().split() + [None] for t in [*texts, texts[12]]]
    held = [zlib.crc32(str(i).encode()) % 7 == 2 for i in [*range(len(texts)), 12]]
    p, c, n, v, tree = slow_tree(tokens, [not h for h in held], 3, 2, 1.0)
    for i, ws in enumerate(tokens[:-1]):
        r = got[i]
        assert (r.held_out, r.n_tokens, r.n_known, r.train_tokens) == (held[i], len(ws), sum(c[(w,)] > 0 for w in ws), n)
        assert r.base_score == pytest.approx(sum(math.log10((c[(w,)] + 1) / (n + v + 1)) for w in ws))
        assert r.score == pytest.approx(sum(math.log10(p(tuple(ws[max(0, j - 3) : j]), w)) for j, w in enumerate(ws)))
    assert sum(tree.values()) > 20 and max(len(k) for k, ok in tree.items() if ok) == 3
    assert score_texts(empty).count() == 0
    lone = score_texts(make(spark, [None]).withColumn("doc_id", F.lit(None).cast("long"))).collect()
    assert len(lone) == 1 and lone[0].n_tokens == 1


def test_suffix_tree_probabilities_sum_to_those_of_the_root():
    texts = [prose(200, s).encode().split() + [None] for s in range(5)]
    p, c, n, v, _ = slow_tree(texts, [True] * 5, 3, 2, 1.0)
    words = [w for (w,) in c]
    for context in [t[i : i + d] for t in map(tuple, texts) for d in (1, 2, 3) for i in range(8)]:
        assert sum(p(context, w) for w in words) + p(context, "new") == pytest.approx(1)


def test_suffix_tree_beats_the_base_on_held_out_texts(spark):
    from quiesce.llm.suffix_tree import score_texts

    folder = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{folder}/documents.parquet")
    base, score = score_texts(docs).filter("held_out").agg(F.sum("base_score"), F.sum("score")).first()
    assert score > base


def test_arrays_as_bytes():
    from quiesce.llm import suffix_tree as S

    keys = np.unique(np.random.default_rng(1).integers(0, 2**63, 999, dtype=np.uint64) * np.uint64(2))
    assert np.array_equal(S.unpacked_keys(S.packed_keys(keys)), keys) and len(S.unpacked_keys(S.packed_keys(keys[:0]))) == 0
    rows = S.questions(7, [keys, np.arange(len(keys))], 5)
    assert np.array_equal(np.concatenate([S.unpacked_keys(k) for k in rows["keys"]]), keys) and rows["bucket"] == sorted(set(rows["bucket"]))


# ---- 2 and 10


def test_quality(spark, empty):
    from quiesce.llm.quality import FactorisationMachine, accepted, features, score_quality

    good = [prose(80, s) for s in range(150)]
    bad = [" | ".join(prose(80, s).upper().split()) + " !!!" for s in range(150)]
    docs = make(spark, [*good, *bad, None, ""])
    labels = spark.createDataFrame([(i, 1 if i < 150 else 0, 0) for i in range(300)] + [(5, None, 0)], "doc_id long, quality int, toxic int")
    got = {r.doc_id: r for r in score_quality(docs, labels).collect()}
    assert len(got) == 302
    held = [i for i in range(300) if got[i].held_out]
    assert held == [i for i in range(300) if zlib.crc32(str(i).encode()) % 5 == 0]
    assert np.mean([got[i].predicted == (i < 150) for i in held]) > 0.95
    assert all(0 <= r.score <= 1 and r.predicted == (r.score >= 0.3) for r in got.values())
    assert {r.score for r in score_quality(docs, labels.limit(0)).collect()} == {0.5}
    assert score_quality(empty, labels).count() == 0
    odd = make(spark, [good[0], good[0], None, prose(20_000, 1)]).withColumn("doc_id", F.when(F.col("doc_id") > 1, F.col("doc_id"))).withColumns({c: F.lit("x") for c in CLASH})
    again = score_quality(odd, labels).collect()
    assert len(again) == 4 and len({r.score for r in again if r.doc_id is None}) == 1
    kept = accepted(odd, labels)
    assert kept.columns == odd.columns and {r.score for r in kept.collect()} <= {"x"}
    # the identity of sum and squares equals the sum over pairs
    m = FactorisationMachine()
    f, x = features("one two three")
    pairs = sum(float(m.v[f[a]] @ m.v[f[b]]) * x[a] * x[b] for a in range(len(f)) for b in range(a))
    assert m.raw(f, x) == pytest.approx(pairs)


def test_language(spark, empty):
    from quiesce.llm.language import predict_language

    kinds = {"aa": ["the", "of", "thing", "was"], "bb": ["über", "und", "nicht", "sch"], "cc": ["что", "это", "как"]}
    rows = []
    for i in range(240):
        lang = list(kinds)[i % 3]
        r = random.Random(i)
        rows.append((i, " ".join(r.choice(kinds[lang]) for _ in range(30)), lang, "s", 0))
    rows += [(300, None, "aa", "s", 0), (301, "123 --", "aa", "s", 0), (302, "the of", None, "s", 0), (303, "", "", "s", 0)]
    got = {r.doc_id: r for r in predict_language(spark.createDataFrame(rows, DOCS)).collect()}
    assert all(got[i].lang_pred == rows[i][2] for i in range(240))
    assert [got[i].lang_pred for i in (300, 301, 302, 303)] == ["und", "und", "aa", "und"]
    assert all(0 <= r.score <= 1 for r in got.values())
    assert {r.lang_pred for r in predict_language(spark.createDataFrame(rows, DOCS).withColumn("lang", F.lit(None).cast("string"))).collect()} == {"und"}
    assert predict_language(empty).count() == 0
    # category L decides what a letter is; no language is left out, however many there are
    marks = [(400, "²", None, "s", 0), (401, "½ ¾ ①", None, "s", 0), (402, "ª", None, "s", 0), (402, "the of " * 30_000, None, "s", 0)]
    name = ["".join(random.Random(i).choices("abcdefghijklmnopqrstuvwxyz", k=9)) for i in range(1010)]
    many = [(1000 + i, f"{name[i]} {name[i][::-1]}", f"l{i:04d}", "s", 0) for i in range(1010)]
    odd = spark.createDataFrame(rows + marks + many, DOCS).withColumns({c: F.lit("x") for c in (*CLASH, "o", "l")})
    got = [(r.doc_id, r.lang_pred) for r in predict_language(odd).collect()]
    assert dict(got[:]).get(400) == dict(got).get(401) == "und" and all(p != "und" for i, p in got if i == 402) and len(got) == len(rows + marks + many)
    learned = {f"l{i:04d}" for i in range(1010) if zlib.crc32(str(1000 + i).encode()) % 4 != 2}
    assert learned <= {p for _, p in got}


def test_language_equals_a_plain_search_of_centroids():
    from quiesce.llm import language as L

    r = random.Random(4)
    texts = [prose(20, s) for s in range(40)] + [" ".join(r.choice(["und", "nicht", "schön"]) for _ in range(20)) for _ in range(40)]
    langs = ["a"] * 40 + ["b"] * 40
    dense = L.frequencies(texts)
    model = L.Centroids([(np.flatnonzero(x).astype(np.uint16), x[x > 0].astype(np.float32)) for x in dense], langs, 3, 0.01, 0.05)
    for t, lang in zip(texts, model.predict(texts)[0]):
        x = L.frequencies([t])[0] * model.idf
        cosine = [sum(a * b for a, b in zip(x, c)) / math.sqrt(sum(a * a for a in x)) for c in model.centres]
        assert lang == model.langs[model.owner[max(range(len(cosine)), key=lambda i: cosine[i])]]


# ---- 4

BASE = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def passes(kind, m):
    d = re.sub("[^0-9]", "", m)
    if kind == "ip":
        return all(int(x) <= 255 for x in m.split("."))
    if kind == "card":
        return 13 <= len(d) <= 19 and sum((int(c) if i % 2 == 0 else int(c) * 2 - 9 * (int(c) > 4)) for i, c in enumerate(reversed(d))) % 10 == 0
    return kind == "email" or 9 <= len(d) <= 15


def test_pii_base_spans(spark, edge, empty):
    from quiesce.llm.pii import find_spans, sanitise

    bits = ["a", "b.", "@", "x", "1", "255", ".", "-", " ", "+", "(", ")", "_", "%", "é", "😀", "\n", "4111 1111 1111 1111", "@b.c", "1.2.3.4", "+1 (222) 555-0199"]
    texts = EDGE + ["".join(rng.choice(bits) for _ in range(rng.randrange(60))) for _ in range(250)] + ["x@y" + ".z" * 3000 + " u@v.w" * 400]
    got = {r.doc_id: r for r in find_spans(make(spark, texts)).collect()}
    for i, t in enumerate(texts):
        spans = [(k, m.start(), m.end()) for k, p in BASE.items() for m in re.finditer(p, t or "") if passes(k, m.group())]
        want = ",".join(f"{k}:{a}:{b}" for k, a, b in spans)
        assert got[i].base_sha256 == hashlib.sha256(want.encode()).hexdigest() and got[i].spans.startswith(want)
        assert got[i].n_email == sum(k == "email" for k, _, _ in spans)
    assert find_spans(empty).count() == 0
    out = sanitise(edge)
    assert out.columns == edge.columns
    for r in out.collect():
        assert r.text == EDGE[r.doc_id] and all(r[c] == "x" for c in CLASH)
    same = make(spark, ["jo@x.org"] * 3).withColumn("doc_id", F.when(F.col("doc_id") > 0, 1)).withColumns({c: F.lit("x") for c in CLASH})
    assert sorted(r.text for r in sanitise(same).collect()) == ["[EMAIL]"] * 3 and find_spans(same).count() == 3


def test_pii_terms(spark):
    from quiesce.llm.pii import find_spans, sanitise

    # "Zorvexia" only ever stands beside an address; "river" is everywhere; "zorv..." words elsewhere keep the head harmless
    texts = [f"river Zorvexia writes from a{i}@b.org" for i in range(12)] + [f"river stone {i} zorvest" for i in range(200)] + ["river Zorvexia alone"]
    docs = make(spark, texts)
    got = {r.doc_id: r for r in find_spans(docs, support=10).collect()}
    at = texts[0].index("Zorvexia")
    assert f"term:{at}:{at + 8}" in got[0].spans and "term:0:5" not in got[0].spans
    assert got[212].spans == ""  # no personal data in it, so nothing to protect
    out = {r.doc_id: r.text for r in sanitise(docs, support=10).collect()}
    assert out[0].startswith("river zorv* ") and out[0].endswith(" [EMAIL]") and out[212] == texts[212]


def test_pii_terms_of_one_address(spark):
    from quiesce.llm.pii import find_spans, sanitise

    # "Zorvexia" stands beside one person's address in three texts only; "Quorndle" is in one text and its copies
    texts = [f"river Zorvexia writes from jo@b.org on day {'abc'[i]}" for i in range(3)] + ["stone Quorndle is with li@b.org"] * 5 + ["stone is with li@b.org too"] + [f"river writes from a{i}@c.org" for i in range(60)] + ["river stone writes from is on day with too"] * 600
    docs = make(spark, texts)
    got = {r.doc_id: r for r in find_spans(docs).collect()}
    assert [got[i].n_term for i in range(3)] == [1, 1, 1] and f"term:{texts[0].index('Zorvexia')}:" in got[0].spans
    assert all(got[i].n_term == 0 for i in range(3, len(texts)))
    assert {r.doc_id: r.text for r in sanitise(docs).collect()}[0] == "river  writes from [EMAIL] on day a"


def test_pii_plan_is_native(spark, edge):
    from quiesce.llm.pii import find_spans

    from quiesce.llm import pii

    seen = []
    stash = pii.stash
    try:
        pii.stash = lambda df: (seen.append(df), stash(df))[1]
        seen.append(find_spans(edge))
    finally:
        pii.stash = stash
    assert len(seen) == 3
    for df in seen:  # what is written on the way, and the result
        assert not re.search("Python|Arrow|Pandas|Cartesian", df._jdf.queryExecution().toString())


# ---- 1


def test_packing(spark, edge, empty):
    from quiesce.llm.packing import pack, pack_shard

    texts = EDGE + [prose(rng.randrange(1, 60), s) for s in range(200)]
    got = pack(make(spark, texts), capacity=64, shard=80).collect()
    bins = collections.defaultdict(list)
    for r in got:
        bins[r.bin_id].append(r)
    norm = [re.sub(r"[\x20\x09-\x0D]+", " ", t or "") for t in texts]
    size = [max(1, len((t or "").encode().split())) for t in texts]
    for rows in bins.values():
        assert sum(r["size"] for r in rows) <= 64
        assert len({r.doc_id % 3 for r in rows}) == len(rows) == len({norm[r.doc_id] for r in rows})
        assert sorted(r.slot for r in rows) == list(range(len(rows)))
    done = collections.Counter()
    for r in got:
        done[r.doc_id] += r["size"]
    assert done == collections.Counter(dict(enumerate(size)))
    assert pack(empty).count() == 0
    # against a plain search of all bins
    r = random.Random(5)
    items = sorted(((r.randrange(1, 30), r.choice("abcd"), r.randrange(40)) for _ in range(400)), reverse=True)
    plain, want = [], []
    for n, s, c in items:
        fits = [b for b in plain if b[0] >= n and s not in b[1] and c not in b[2]]
        left = min((b[0] for b in fits), default=None)
        want.append(None if left is None else left - n)
        b = next((b for b in fits if b[0] == left), None)
        if b is None:
            b = [50, set(), set()]
            plain.append(b)
        b[0] -= n
        b[1].add(s)
        b[2].add(c)
    b, _ = pack_shard([x[0] for x in items], [x[1] for x in items], [x[2] for x in items], 50)
    left, seen = {}, []
    for (n, _, _), k in zip(items, b.tolist()):
        seen.append(None if k not in left else left[k] - n)
        left[k] = left.get(k, 50) - n
    # where several bins are equally tight either may be taken, so choices may part later; until then they agree
    same = next((i for i, (x, y) in enumerate(zip(seen, want)) if x != y), len(want))
    assert same >= 40 and len(left) <= len(plain) + 3
    # without conflicts there is nothing to part them: every piece is placed as tightly as by the plain search
    sizes = sorted((r.randrange(1, 30) for _ in range(400)), reverse=True)
    free, want = [], []
    for n in sizes:
        k = min((i for i, x in enumerate(free) if x >= n), key=lambda i: free[i], default=None)
        want.append(None if k is None else free[k] - n)
        if k is None:
            free.append(50 - n)
        else:
            free[k] -= n
    b, _ = pack_shard(sizes, [None] * 400, list(range(400)), 50)
    left, seen = {}, []
    for n, k in zip(sizes, b.tolist()):
        seen.append(None if k not in left else left[k] - n)
        left[k] = left.get(k, 50) - n
    assert seen == want
    # rows that repeat, and rows without id or source
    from quiesce.llm.packing import fill

    odd = make(spark, ["one two"] * 30, 0).withColumns({"doc_id": F.lit(4).cast("long"), "source": F.lit(None).cast("string")}).unionByName(make(spark, ["x"]).withColumn("doc_id", F.lit(None).cast("long"))).withColumns({c: F.lit("x") for c in CLASH})
    rows = pack(odd, capacity=64, shard=10)
    assert rows.count() == 31 and rows.groupBy("bin_id").agg(F.count_if(F.col("doc_id") == 4).alias("k")).agg(F.max("k")).first()[0] == 1
    assert fill(rows, 64).first().pieces == 31


# ---- 5


def test_multi_index(spark):
    from quiesce.llm.multi_index import search

    g = np.random.default_rng(2)
    x = g.normal(size=(1200, 16)).astype(np.float32)
    x[100:400] = x[100]  # a hot vector
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5050, [0.0] * 16), (5100, [float("nan")] * 16), (5150, [None] * 16), (5200, [1.0])]
    rows += [(None, x[0].tolist()), (50, x[50].tolist())]  # no id; a repeated row
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>").withColumns({c: F.lit("x") for c in ("id", "v", "cell", "asks", "score", "rank")})
    got = collections.defaultdict(list)
    for r in search(df, F.col("vec_id") % 50 == 0, words=16, shelf_rows=100, probes=24).collect():
        got[r.query_id].append((r["rank"], r.vec_id, r.score))
    y = x.astype(float)
    n = np.sqrt((y * y).sum(1))
    hits = 0
    assert set(got) == set(range(0, 1200, 50))
    for q, found in got.items():
        s = (y * y[q]).sum(1) / (n * n[q])
        s[q] = -9
        best = np.lexsort((np.arange(1200), -s))[:5]
        found.sort()
        assert [k for k, _, _ in found] == [1, 2, 3, 4, 5]
        assert all(abs(s[v] - c) < 1e-12 for _, v, c in found)
        hits += len({v for _, v, _ in found} & set(best.tolist()))
    assert hits / (5 * len(got)) >= 0.9
    assert [v for _, v, _ in got[150]] == [100, 101, 102, 103, 104]
    few = search(df.filter("vec_id < 3"), F.col("vec_id") == 0).collect()
    assert {r.vec_id for r in few} == {1, 2}
    assert search(df.filter("vec_id >= 5000"), F.lit(True)).count() == 0


def test_multi_index_shelves_hold_all_cells():
    from quiesce.llm.multi_index import shelves

    rows = np.array([3, 0, 950, 40, 70, 1, 100, 250])
    first, splits = shelves(rows, 100)
    assert splits.tolist() == [1, 1, 10, 1, 1, 1, 1, 3]
    load = collections.Counter()
    for f, s, n in zip(first.tolist(), splits.tolist(), rows.tolist()):
        for j in range(s):
            load[f + j] += -(-n // s)
    assert max(load.values()) <= 100


def test_multi_index_visits_cells_in_order():
    from quiesce.llm.multi_index import Codebooks, distances

    x = np.random.default_rng(3).normal(size=(500, 8))
    books = Codebooks(x, 8)
    q = x[3]
    order = books.visit(q, [1] * 64, 64)
    total = (distances(q[None, :4], books.first)[0][:, None] + distances(q[None, 4:], books.second)[0][None, :]).ravel()
    assert sorted(order) == list(range(64)) and np.all(np.diff(total[order]) >= -1e-12)


# ---- 3


def test_revisits(spark):
    from quiesce.llm.revisit import canonical_url, resolve_revisits

    schema = "record_id long, url string, ts long, kind string, etag string, last_modified string, digest string, headers map<string,string>, extra string"
    h = {"Content-Type": "text/html", "Content-Length": "9", "ETag": "e1"}
    rows = [
        (1, "http://www.A.com/x/?b=2&a=1#f", 10, "response", '"e1"', None, "d1", h, ""),
        (2, "https://a.com:443/x?a=1&b=2&utm_source=q", 20, "revisit", 'W/"e1"', None, None, {"date": "now", "content-length": "0", "etag": "e2"}, ""),
        (3, "a.com/x?a=1&b=2", 5, "revisit", '"e1"', None, None, None, ""),
        (4, "a.com/x?a=1&b=2", 10, "revisit", '"e1"', None, None, None, ""),
        (5, "a.com/x?a=1&b=2", 900, "response", '"e9"', None, "d9", h, ""),
        (6, "a.com/x?a=1&b=2", 1000, "revisit", '"e1"', None, None, None, ""),
        (7, "a.com/x?a=1&b=2", 899, "revisit", None, None, None, None, ""),
        (8, None, 50, "revisit", None, None, None, None, ""),
        (9, "a.com/y", None, "revisit", None, None, None, None, ""),
        (10, "a.com/x?a=1&b=2", 901, "revisit", None, None, "d9", {}, ""),
    ]
    df = spark.createDataFrame(rows, schema)
    assert {r[0] for r in df.filter("record_id < 8").select(canonical_url(F.col("url"))).collect()} == {"a.com/x?a=1&b=2"}
    for slices in (1, 7, 64):
        got = {r.record_id: r for r in resolve_revisits(df, slices).collect()}
        assert {i: r.status for i, r in got.items()} == {2: "resolved", 3: "no_original", 4: "no_original", 6: "mismatch", 7: "unverified", 8: "no_original", 9: "no_original", 10: "resolved"}
        assert got[2].original_id == 1 and got[7].original_id == 1 and got[10].original_id == 5
        assert got[2].headers == {"Content-Type": "text/html", "Content-Length": "9", "date": "now", "etag": "e2"}
    assert resolve_revisits(df.limit(0)).count() == 0
    # a hot URL in a burst, repeated rows and clashing names, against a plain search
    r = random.Random(6)
    burst = [(100 + i, "a.com/h", 1_000_000 + r.randrange(40) if i % 3 else r.randrange(2_000_000), r.choice(["response", "revisit"]), None, None, f"d{r.randrange(2)}", None, "") for i in range(300)]
    burst += [(5, "a.com/h", 1_000_020, "revisit", None, None, "d0", None, "")] * 3
    many = spark.createDataFrame(burst, schema).withColumns({c: F.lit("x") for c in ("u", "slice", "o", "full", "near", "best")})
    found = resolve_revisits(many).collect()
    assert len(found) == sum(b[3] == "revisit" for b in burst)
    for x in found:
        earlier = [(b[2], b[0]) for b in burst if b[3] == "response" and b[2] < x.ts]
        assert (x.original_ts, x.original_id) == (max(earlier) if earlier else (None, None))


def test_simhash_forests_against_plain_union():
    import numpy as np

    from quiesce.llm.simhash import _forest

    rng = np.random.default_rng(5)
    for _ in range(100):
        ids = rng.integers(-(10**9), 10**9, rng.integers(2, 60))
        a, b = rng.choice(ids, 50), rng.choice(ids, 50)
        least = {i: i for i in ids.tolist()}
        changed = True
        while changed:
            changed = False
            for x, y in zip(a.tolist(), b.tolist()):
                low = min(least[x], least[y])
                changed |= least[x] != low or least[y] != low
                least[x] = least[y] = low
        met = set(a.tolist()) | set(b.tolist())
        got = _forest(a, b)
        assert dict(zip(got.column(0).to_pylist(), got.column(1).to_pylist())) == {i: least[i] for i in met if least[i] != i}


def test_different_values_are_found_by_any_sort():
    from quiesce.llm import suffix_tree

    rng = np.random.default_rng(4)
    for n in (0, 1, 5000):
        a = rng.integers(0, 700, n).astype(np.uint64) << np.uint64(54)
        values, some, place = suffix_tree.distinct(a)
        assert values.tolist() == sorted(set(a.tolist()))
        assert (a[some] == values).all() and (values[place] == a).all()


def test_the_classifier_reads_its_rows_where_they_lie(spark, monkeypatch):
    """The driver holds the fitted rows in the narrow types that the tasks sent, and learns the same from them."""
    from quiesce.llm import quality

    seen, learn = [], quality.FactorisationMachine.fit

    def fit(self, rows, labels, **options):
        seen.extend(rows)
        return learn(self, rows, labels, **options)

    monkeypatch.setattr(quality.FactorisationMachine, "fit", fit)
    docs = spark.createDataFrame([(i, f"word{i} plain text {'junk ' * (i % 2) * 5}") for i in range(30)], "doc_id long, text string")
    labels = spark.createDataFrame([(i, i % 2) for i in range(30)], "doc_id long, quality int")
    machine = quality.fit(docs, labels, "doc_id", "text", "quality", 5, 100)
    assert seen and {(f.dtype.str, x.dtype.str) for f, x in seen} == {("<u2", "<f4")}
    y = np.array([r for r in labels.filter("doc_id >= 0").select("quality").toPandas()["quality"]], float)[: len(seen)]
    wide = [(f.astype(np.int64), x.astype(float)) for f, x in seen]
    a, b = (learn(quality.FactorisationMachine(), rows, y) for rows in (seen, wide))
    assert machine.b != 0 and (a.w == b.w).all() and (a.v == b.v).all() and a.b == b.b


def test_a_stashed_table_keeps_no_shuffle(spark):
    from quiesce.llm import common

    shuffles = spark._jvm.org.apache.spark.SparkEnv.get().mapOutputTracker().shuffleStatuses()
    df = spark.range(1000).groupBy((F.col("id") % 7).alias("k")).agg(F.count(F.lit(1)).alias("n"))
    before, setting = shuffles.size(), spark.conf.get(common._CLEAN)
    assert sorted(map(tuple, common.stash(df).collect())) == sorted(map(tuple, df.collect()))
    kept = shuffles.size()
    common.stash(df)
    assert shuffles.size() == kept == before + 1 and spark.conf.get(common._CLEAN) == setting  # one of df.collect()


def test_tokens_numbered_by_arrays_are_those_of_each_text():
    from quiesce.llm import suffix_tree as S

    odd = ["", " ", "\n\n", " a", "a ", "A  b\x0bC\x0c\r\n d", "Ü x\x1cy", "a\x00 \x00", "x"]
    rng = random.Random(6)
    for texts in [odd, *(rng.choices(odd, k=4) for _ in range(50))]:
        words, numbers, sizes = S.numbered_tokens([t.encode() for t in texts])
        want = [S.tokens(t) for t in texts]
        assert [w if w == S.END else w[:-1] for w in words[numbers]] == sum(want, []) and sizes.tolist() == list(map(len, want))
        assert len(set(words)) == len(words)


def test_different_values_that_differ_in_their_last_bits_only():
    from quiesce.llm import suffix_tree

    a = np.random.default_rng(5).integers(0, 700, 5000).astype(np.uint64) + np.uint64(2**63)
    values, some, place = suffix_tree.distinct(a)
    assert values.tolist() == sorted(set(a.tolist())) and (a[some] == values).all() and (values[place] == a).all()


def test_a_walk_sorts_nothing_but_strings(monkeypatch):
    """A block's tokens are sorted once for each depth: the places of contexts follow from the strings of the depth before."""
    from quiesce.llm import suffix_tree as S

    _, numbers, sizes = S.numbered_tokens([prose(300, s).encode() for s in range(4)])
    keys = np.sort(np.random.default_rng(2).integers(0, 2**63, numbers.max() + 1, dtype=np.uint64))
    block = S.Block(S.packed_keys(keys), S.packed(numbers.astype(np.int32)), sizes, np.zeros(4, bool))
    calls, sort, told = [], S.distinct, {}
    for step in (0, 2, 3, 4, 5):
        question = S.walk(block, told, float(sizes.sum()), float(len(keys)), 2, 2)[0]
        assert (question[0][1:] > question[0][:-1]).all()
        sums = S.sums([question[0]], [question[1:]])[0][0]
        told[step] = S.passing(*sums[:3], 0.0) if step % 2 else sums[:2]
    monkeypatch.setattr(S, "distinct", lambda a: calls.append(len(a)) or sort(a))
    nothing, p, _ = S.walk(block, told, float(sizes.sum()), float(len(keys)), 2, 2)
    assert nothing == [] and len(p) == len(numbers) and (p > 0).all() and (p <= 1).all()
    assert len(calls) == 2 and len(numbers) >= calls[0] >= calls[1] > 0
