"""The registered queries on a small table, against brute force that shares no code with them."""

import hashlib
import math
import random
import re
import struct
import zlib
from collections import Counter, defaultdict

import duckdb
import numpy as np
import public_tokenizers
import pytest
import xxhash
from tokenizers import Tokenizer

from gridlake.llm import impact_topk, jaccard_join, pii_supervision, quality_resampling, queries, secret_ledger, stages, textkernels, url_filter
from gridlake.llm.common import Scratch, components

SF = "/root/testdata/sf0.001"


@pytest.fixture(scope="module")
def library():
    return Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))


@pytest.fixture(scope="module")
def corpus(spark):
    return {r.doc_id: r.text or "" for r in spark.read.parquet(f"{SF}/documents.parquet").collect()}


def run(spark, name):
    return queries.queries()[name](spark, SF)


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql(spark, name):
    con = duckdb.connect()
    for t in ("documents", "embeddings"):
        con.execute(f"CREATE VIEW {t} AS SELECT * FROM '{SF}/{t}.parquet'")
    want = con.execute(queries.oracle_sql()[name]).df()
    got = run(spark, name).toPandas()[list(want.columns)]
    assert sorted(map(tuple, got.to_numpy().tolist())) == sorted(map(tuple, want.to_numpy().tolist()))


def test_op1(spark, corpus):
    """Counts, weights, threshold and selection worked out document by document."""
    got = {r.doc_id: r for r in run(spark, "op1_importance_resampling").collect()}
    labels = {r.doc_id: r.quality for r in spark.read.parquet(f"{SF}/labels.parquet").collect()}
    grams = {}
    for k, t in corpus.items():
        data = np.frombuffer(t.encode(), np.uint8)
        w = [int(x) for x in textkernels.word_hashes(data, np.array([0, len(data)]))[0]]
        pairs = [int(quality_resampling.mixed(np.array([(a * 3 + b) % 2**64], np.uint64))[0]) for a, b in zip(w, w[1:], strict=False)]
        grams[k] = [x % quality_resampling.BUCKETS for x in w + pairs]
    raw, target = Counter(x for g in grams.values() for x in g), Counter(x for k, g in grams.items() if labels.get(k) == 1 for x in g)
    n, m, b = sum(raw.values()), sum(target.values()), quality_resampling.BUCKETS
    weight = {k: sum(math.log((target[x] + 1) / (m + b)) - math.log((raw[x] + 1) / (n + b)) for x in g) / (len(g) + quality_resampling.SHRINK) for k, g in grams.items()}
    for k, g in grams.items():
        assert got[k].n_grams == len(g) and math.isclose(got[k].weight, weight[k], rel_tol=1e-9, abs_tol=1e-12)
    scored = sorted((got[k].weight, q) for k, q in labels.items() if k in got)
    cost = [(8.0 * sum(q for _, q in scored[:i]) + sum(1 - q for _, q in scored[i:]), i) for i in range(len(scored) + 1)]
    i = min(cost)[1]
    at = (scored[i - 1][0] + scored[i][0]) / 2 if 0 < i < len(scored) else (scored[0][0] - 1 if i == 0 else scored[-1][0])
    k = sum(r.weight >= at for r in got.values())
    first = sorted(got, key=lambda d: (-got[d].gumbel_key, d))[:k]
    assert {d for d, r in got.items() if r.selected} == set(first)


def test_op1_ids(spark):
    """Ids beyond 2^53 beside a null one, and a labelled -1."""
    big = 2**53 + 1
    docs = spark.createDataFrame([(big, "a b c"), (None, "x y z"), (-1, "q r"), (7, "s")], "doc_id long, text string").coalesce(1)
    with Scratch(spark, "t") as s:
        _, target = quality_resampling.gram_counts(quality_resampling.keyed(s, docs), {big: 1, -1: 1})
    assert target.sum() == 5 + 3


ASSIGN = re.compile(r"""((?ai:password|passwd|secret|token|api_?key))["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""")


def secrets(t):
    out = [(m.start(), 0, m.end()) for m in ASSIGN.finditer(t) if len(m[2]) >= 6]
    out += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 20]
    return sorted(out + [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 24])


def test_op2(spark, corpus):
    got = {r.doc_id: r for r in run(spark, "op2_secret_ledger").collect()}
    assert got.keys() == corpus.keys()
    for k, t in corpus.items():
        base = secrets(t)
        said = ",".join(f"{('assign', 'access', 'hex')[x]}:{a}:{b}" for a, x, b in base)
        assert got[k].base_sha256 == hashlib.sha256(said.encode()).hexdigest() and set(filter(None, said.split(","))) <= set(got[k].spans.split(","))
        assert (got[k].n_assign, got[k].n_access, got[k].n_hex) == tuple(sum(x == j for _, x, _ in base) for j in range(3))


def test_op2_counts(spark):
    """Each kind is counted by its own, at any place among the findings."""
    texts = ["password=abcdef", f"{'a1' * 12} AKIA{'Z' * 16}", f"AKIA{'Z' * 16} token: abcdef secret=abcdef", "-----BEGIN PRIVATE KEY----- passwd=abcdef", "secret=abc", None]
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    with Scratch(spark, "t") as s:
        got = {r.doc_id: (r.n_assign, r.n_access, r.n_hex) for r in secret_ledger.ledger_scan(s, docs)[0].collect()}
    assert got == {0: (1, 0, 0), 1: (0, 1, 1), 2: (2, 1, 0), 3: (1, 0, 0), 4: (0, 0, 0), 5: (0, 0, 0)}


def test_op2_versions(spark):
    """A later version of a path, a new path with an old blob and a new rule version."""
    key = "-----BEGIN RSA PRIVATE KEY----- eyJabcdefghij.eyJabcdefghij.abcdefghij password=abcdef12"
    one = spark.createDataFrame([(1, key), (2, "plain"), (3, None)], "doc_id long, text string")
    two = spark.createDataFrame([(1, key), (1, key + " x"), (9, key), (2, "plain"), (4, "")], "doc_id long, text string")
    with Scratch(spark, "t") as s:
        first, ledger = secret_ledger.ledger_scan(s, one, versions=("base-1",))
        assert ledger.count() == 3 and {r.spans.count(":") for r in first.where("doc_id = 1").collect()} == {2}
        got, fresh = secret_ledger.ledger_scan(s, two, ledger, versions=("base-1",))
        assert fresh.count() == 1 and got.count() == 5
        got, more = secret_ledger.ledger_scan(s, two, ledger.unionByName(fresh))
        assert Counter(r.rule_version for r in more.collect()) == {"added-1": 4}
        kinds = {tuple(x.split(":")[0] for x in r.spans.split(",")) for r in got.where("doc_id IN (1, 9)").collect()}
    assert kinds == {("private_key", "jwt", "assign")}


def luhn(d):
    return sum(x if i % 2 == 0 else 2 * x - 9 * (x > 4) for i, x in enumerate(map(int, reversed(d)))) % 10 == 0


def card(rng, good):
    while luhn(d := "4" + "".join(rng.choice("0123456789") for _ in range(15))) != good:
        pass
    return d


def test_op3_classifier(spark):
    """Loose spans of all four kinds: true ones are added, false ones are not."""
    rng, true, false, plain = random.Random(3), [], [], []
    for k in range(30):
        good, bad = ((d := card(rng, ok))[:4] + f".{d[4:8]}.{d[8:12]}.{d[12:]}" for ok in (True, False))
        true += [("write to ", f"name{k} [at] host{k} [dot] com", " today"), ("the server ip is ", f"10[.]0[.]{k}[.]7", " now"), ("pay by card ", good, " soon"), ("call me: ", f"212-555-{1000 + k}", " please")]
        false += [("we ", f"look at this{k} dot then{k}", " go"), ("range ", f"300-400-{500 + k}-600", " of"), ("no ", bad, " part"), ("item ", f"000-123-{1000 + k}", " rev")]
        plain.append((f"mail a{k}@b.org or +1 (212) 555-{1000 + k} or {card(rng, True)} at 10.0.0.{k}", "", ""))
    rows = [(i, "".join(x)) for i, x in enumerate(true + false + plain)]
    with Scratch(spark, "t") as s:
        got = {r.doc_id: r.spans for r in pii_supervision.report(s, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    kinds = ("email", "ip", "card", "phone")
    for i, (ahead, body, _) in enumerate(true + false):
        assert got[i] == (f"{kinds[i % 4]}:{len(ahead)}:{len(ahead) + len(body)}" if i < len(true) else ""), rows[i]
    for i in range(len(true + false), len(rows)):
        assert [x.split(":")[0] for x in got[i].split(",")] == ["email", "phone", "card", "ip"]


def test_op3_long_texts(spark):
    texts = ["a@b" + ".c" * 100_000, "1" * 1_000_000, "u@h.com " * 40_000, "x@y.org 555-222-3333 " * 20_000, "1 " * 300_000, "+1" * 200_000]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    with Scratch(spark, "t") as s:
        got = {r.doc_id: r for r in pii_supervision.report(s, df).collect()}
        found = s.save(pii_supervision.with_candidates(df), "found")
        done = {r.doc_id: r.text for r in pii_supervision.redacted(found, pii_supervision.fit_table(found)).collect()}
    assert [got[k].n_email for k in range(6)] == [1, 0, 40_000, 20_000, 0, 0]
    assert done[0] == "[EMAIL]" and done[2] == "[EMAIL] " * 40_000 and done[3].startswith("[EMAIL] ") and "@" not in done[3]
    assert [done[k] == texts[k] for k in (1, 4, 5)] == [True] * 3


def test_op4(spark, corpus):
    got = {r.doc_id: r for r in run(spark, "op4_suffix_array").collect()}
    bodies = {k: t.encode() for k, t in corpus.items()}
    found = Counter(hash(b[i : i + 200]) for b in bodies.values() for i in range(len(b) - 199))
    for k, b in bodies.items():
        mark = bytearray(len(b))
        for i in range(len(b) - 199):
            if found[hash(b[i : i + 200])] > 1:
                mark[i : i + 200] = b"\1" * 200
        runs = sum(1 for i, m in enumerate(mark) if m and (i == 0 or not mark[i - 1]))
        kept = bytes(x for x, m in zip(b, mark, strict=True) if not m)
        assert (got[k].n_bytes, got[k].n_removed, got[k].n_spans, got[k].kept_sha256) == (len(b), sum(mark), runs, hashlib.sha256(kept).hexdigest())


def test_op5_edges(spark):
    schema = "vec_id long, embedding array<double>, rid long, block long, asks long"
    rng = np.random.default_rng(3)
    rows = [(k // 2, rng.normal(0, 0.2, 8).tolist(), 1, 1, 1) for k in range(300)] + [(None, [1.0] * 8, 1, 1, 1), (50, [], 1, 1, 1), (100, [0.5] * 3, 1, 1, 1)]
    with Scratch(spark, "t") as s:
        assert impact_topk.search(s, spark.createDataFrame([], schema)).count() == 0
        got = impact_topk.search(s, spark.createDataFrame(rows, schema), block=40, query_block=2).toPandas()
    use = [(v, np.floor(256 * np.pad(np.array(x), (0, 8 - len(x)))).astype(int)) for v, x, *_ in rows if v is not None and x]
    want = Counter()
    for i, (q, x) in enumerate(use):
        if q % 50 == 0:
            best = sorted((-int(x @ y), v) for j, (v, y) in enumerate(use) if j != i)[:5]
            want.update((q, r + 1, v, -s) for r, (s, v) in enumerate(best))
    assert Counter(map(tuple, got[["query_id", "rank", "vec_id", "score"]].to_numpy().tolist())) == want


def test_op6(spark, corpus, library):
    got = {r.doc_id: r for r in run(spark, "op6_bpe_dp").collect()}
    for k, t in corpus.items():
        ids = library.encode(t, add_special_tokens=False).ids
        assert got[k].n_tokens == len(ids) and got[k].ids_sha256 == hashlib.sha256(struct.pack(f"<{len(ids)}I", *ids)).hexdigest()
        assert got[k].decoded_sha256 == hashlib.sha256(library.decode(ids, skip_special_tokens=False).encode()).hexdigest()


def test_op6_edges(spark, docs, texts, empty, library):
    from gridlake.llm import bpe_dp

    path = public_tokenizers.path("byte_bpe_50k.json")
    want = Counter(hashlib.sha256(struct.pack(f"<{len(x)}I", *x)).hexdigest() for x in (library.encode(t or "", add_special_tokens=False).ids for t in texts))
    assert Counter(r.ids_sha256 for r in bpe_dp.digest_documents(docs, path).collect()) == want
    assert bpe_dp.digest_documents(empty, path).count() == 0


def test_op7(spark, corpus):
    import unicodedata

    got, ids = {r.doc_id: r for r in run(spark, "op7_exact_digest").collect()}, sorted(corpus)

    def printed(t):
        t = unicodedata.normalize("NFKC", unicodedata.normalize("NFKC", t).casefold())
        return xxhash.xxh3_128_hexdigest(" ".join(t.split()).encode())

    groups = defaultdict(list)
    for k in ids:
        groups[printed(corpus[k])].append(k)
    for k, after in zip(ids, ids[1:] + ids[:1], strict=True):
        t, following = corpus[k], corpus[after]
        new = t[: len(t) - len(t) // 2] + following[: len(t) // 2]
        r, own = got[k], printed(t)
        assert (r.n_chars, r.edited_sha256) == (len(t), hashlib.sha256(new.encode()).hexdigest())
        assert (r.fingerprint, r.edited_fingerprint) == (own, printed(new))
        assert (r.near_edited, r.near_next) == (float(own == printed(new)), float(own == printed(following)))
        assert (r.group_id, r.group_size) == (groups[own][0], len(groups[own]))


def test_op8(spark, corpus, library):
    got = run(spark, "op8_best_fit").toPandas()
    total = 0
    for k, own in got.groupby("doc_id"):
        ids = library.encode(corpus[k], add_special_tokens=False).ids + [0]
        total += len(ids)
        own = own.sort_values("piece")
        assert own.start.tolist() == np.concatenate(([0], own.length.cumsum().tolist()[:-1])).tolist() and own.length.sum() == len(ids)
        assert (len(own) == 1 or (own.length.iloc[1:] == 2048).all()) and own.length.max() <= 2048
        for p in own.itertuples():
            assert p.ids_crc32 == zlib.crc32(struct.pack(f"<{p.length}I", *ids[p.start : p.start + p.length]))
    assert set(got.doc_id) == set(corpus)
    for _, b in got.groupby("sequence_id"):
        b = b.sort_values("offset")
        assert b.offset.tolist() == np.concatenate(([0], b.length.cumsum().tolist()[:-1])).tolist() and b.length.sum() <= 2048
    assert got.sequence_id.nunique() <= -(-total // 2048) + 1


def test_op9_words_not_hashes(spark):
    """Words on which a polynomial modulo 2^64 gives one value, and a very long text."""
    bits = [0]
    while len(bits) < 1024:
        bits += [1 - b for b in bits]
    a, b = ("".join(x[k] for k in bits) for x in ("ab", "ba"))
    long = " ".join(f"w{k}" for k in range(100_000))
    rows = [(1, a), (2, b), (3, a.upper()), (4, long), (5, long + " x"), (6, "z" * 500_000), (7, "z" * 500_001)]
    with Scratch(spark, "t") as s:
        got = {r.doc_id: r.component_id for r in jaccard_join.join_components(s, spark.createDataFrame(rows, "doc_id long, text string")).collect()}
    assert got == {1: 1, 2: 2, 3: 1, 4: 4, 5: 4, 6: 6, 7: 7}
    same = textkernels.Words(b"one two three four five six")
    other = textkernels.Words(b"one two three four five six")
    other.low = textkernels.Words(b"one two three four five sax").low
    assert not textkernels.unmixed(same, other) and not textkernels.similar(same, other, 80)[1]


def test_op9_hot_key(spark):
    """One shingle in all sets, so that its list is cut into tiles."""
    rng = random.Random(5)
    texts = [f"all texts begin with this {' '.join(f'v{rng.randrange(9)}' for _ in range(rng.randint(0, 3)))}" for _ in range(240)]
    sets = [frozenset(tuple(t.split()[k : k + 5]) for k in range(len(t.split()) - 4)) for t in texts]
    root = list(range(len(texts)))
    for _ in range(len(texts)):
        before = list(root)
        for i, a in enumerate(sets):
            for j, b in enumerate(sets):
                if 100 * len(a & b) >= 80 * len(a | b):
                    root[i] = min(root[i], root[j])
        if before == root:
            break
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")
    with Scratch(spark, "t") as s:
        got = jaccard_join.join_components(s, df, tile=20).toPandas().sort_values("doc_id")
    assert got.component_id.tolist() == root


def test_components_fail_openly(spark):
    with Scratch(spark, "t") as s, pytest.raises(RuntimeError):
        components(s, spark.createDataFrame([(k, k + 1) for k in range(200)], "a long, b long"), rounds=2)


def test_op10(spark):
    pages = {r.page_id: r.url or "" for r in spark.read.parquet(f"{SF}/pages.parquet").collect()}
    got = {r.page_id: r for r in run(spark, "op10_url_filter").collect()}
    rules = {"org/": "allow", "example.org/es/": "block", "example.org/en/1": "block", "com/fr/": "allow", "com/de/": "block"}
    parts = {}
    for k, u in pages.items():
        rest = u.split("://", 1)[1] if "://" in u else ""
        host = re.match("[^/?#]*", rest)[0]
        parts[k] = re.sub("[A-Z]", lambda m: m[0].lower(), host), re.match("[^?#]*", rest[len(host) :])[0]
    for k, (host, path) in parts.items():
        fits = [r for r in rules if (host == r.split("/")[0] or host.endswith("." + r.split("/")[0])) and path.startswith(r[r.index("/") :])]
        rule = max(fits, key=len, default=None)
        assert (got[k].host, got[k].path, got[k].rule) == (host, path, rule)
        assert got[k].verdict == (rules[rule] if rule else "block" if got[k].block_score > 0 else "allow")
    # the classifier, worked out with plain dictionaries
    counts, total = url_filter.word_counts(spark.read.parquet(f"{SF}/pages.parquet"))
    split = url_filter.Segmenter(counts, total)
    words = {k: Counter(url_filter.tokens(*p, split)) for k, p in parts.items()}
    seen, docs = {"allow": Counter(), "block": Counter()}, Counter()
    for k, (host, _) in parts.items():
        label = "block" if any(w in host for w in url_filter.UNWANTED) else rules.get(got[k].rule)
        if label:
            docs[label] += 1
            seen[label] += words[k]
    size = {c: sum(x.values()) + url_filter.BUCKETS for c, x in seen.items()}
    for k in pages:
        score = math.log((docs["block"] + 1) / (docs["allow"] + 1)) + sum(n * (math.log((seen["block"][t] + 1) / size["block"]) - math.log((seen["allow"][t] + 1) / size["allow"])) for t, n in words[k].items())
        assert math.isclose(got[k].block_score, score, rel_tol=1e-9, abs_tol=1e-9)


def test_op10_edges(spark):
    schema = "page_id long, url string, html string, rule string, verdict string, token long"
    rows = [(1, "http://a.com/de/x", None, "x", "y", 1), (1, "http://a.com/de/x", "<p>x", "x", "y", 1), (None, None, "", "x", "y", 1), (2, "HTTP://" + "a" * 50_000 + ".net/", "t", None, None, 1)]
    got = url_filter.judge(spark.createDataFrame(rows, schema)).collect()
    assert Counter((r.page_id, r.rule) for r in got) == {(1, "com/de/"): 2, (None, None): 1, (2, None): 1}
    assert url_filter.judge(spark.createDataFrame([], schema)).count() == 0


@pytest.mark.parametrize("name, stage", stages.STAGES)
def test_stage_edges(spark, docs, empty, name, stage):
    """Nulls, repeated and missing ids, clashing columns and no rows at all."""
    got = stage(spark, docs, SF)
    if name != stages.STAGES[-1][0]:
        assert got.columns == docs.columns and 0 < got.count() <= docs.count()
        if name in ("suffix-array dedup", "PII"):
            assert got.count() == docs.count()
    else:
        assert got.where("piece = 0").count() == docs.count()
    assert stage(spark, empty, SF).count() == 0
