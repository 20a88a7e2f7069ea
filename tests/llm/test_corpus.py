"""Operators against brute force, with nulls, empty and odd texts, repeated rows
and further columns."""

import hashlib
import random
import re
import zlib
from collections import Counter

import numpy as np
import pytest
from pyspark.sql import functions as F

from querymend.llm import decontam, embed_dedup, jaccard_join, langid, packing, pii, quality, secrets, suffix_dedup, url_filter

SF = "/root/testdata/sf0.001"
ODD = [(-1, None), (-2, ""), (-3, "a b"), (-4, "A  b"), (-5, "ab" * 300), (-6, "é\0 " * 150), (-7, "a@b.c_d@e.f 1.2.3.4.5.6.7.8 +1 (555) 010-9999 4111 1111 1111 1111 "), (-8, 'é API_KEY = "abcdefgh1" ' + "0" * 40 + " AKIA" + "A" * 16), (-9, "1 " * 20000), (-9, "1 " * 20000)]


@pytest.fixture(scope="module")
def docs(spark):
    odd = spark.createDataFrame([(i, t, "x", "y", "z") for i, t in ODD], "doc_id long, text string, lang string, source string, score string")
    real = spark.read.parquet(f"{SF}/documents.parquet").selectExpr("doc_id", "text", "lang", "source", "'z' AS score")
    return real.unionAll(odd).cache()


@pytest.fixture(scope="module")
def texts(docs):
    return {r.doc_id: r.text or "" for r in docs.collect()}


def digest(spans):
    return hashlib.sha256(",".join(f"{k}:{a}:{b}" for a, _, k, b in sorted(spans)).encode()).hexdigest()


def test_pii(docs, texts):
    def brute(t):
        out = [(m.start(), 0, "email", m.end()) for m in re.finditer(r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", t)]
        out += [(m.start(), 1, "ip", m.end()) for m in re.finditer(r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", t) if all(int(p) < 256 for p in m[0].split("."))]
        for m in re.finditer(r"[0-9]([\x20-]?[0-9])+", t):
            d = [int(c) for c in re.sub("[^0-9]", "", m[0])][::-1]
            if 14 <= len(d) <= 19 and sum(x if i % 2 == 0 else 2 * x - 9 * (x > 4) for i, x in enumerate(d)) % 10 == 0:
                out.append((m.start(), 2, "card", m.end()))
        return out + [(m.start(), 3, "phone", m.end()) for m in re.finditer(r"\+[0-9][\x20().0-9-]+[0-9]", t) if 10 <= len(re.sub("[^0-9]", "", m[0])) <= 15]

    for r in pii.pii_digest(docs).collect():
        assert r.base_sha256 == digest(brute(texts[r.doc_id])), r.doc_id


def test_secrets_and_ledger(spark, docs, texts, tmp_path):
    def brute(t):
        out = [(m.start(), 0, "assign", m.end()) for m in re.finditer(secrets.BASE_RULES[0].pattern, t) if len(m[1]) >= 8]
        out += [(m.start(), 1, "access", m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 16]
        return out + [(m.start(), 2, "hex", m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 32]

    ledger = secrets.BlobLedger(spark, f"file://{tmp_path}/ledger")
    first = secrets.secrets_digest(docs, ledger).collect()
    for r in first:
        assert r.base_sha256 == digest(brute(texts[r.doc_id])), r.doc_id
    known = ledger.findings("r1").count()
    assert known == len({hashlib.sha256(t.encode()).digest() for t in texts.values()})
    again = secrets.secrets_digest(docs, ledger).collect()
    assert sorted(map(str, first)) == sorted(map(str, again)) and ledger.findings("r1").count() == known


def test_account_numbers_in_running_text(spark):
    de, gb, no = "DE89 3704 0044 0532 0130 00", "GB82 WEST 1234 5698 7654 32", "NO9386011117947"
    packed = gb.replace(" ", "")
    rows = [
        (f"{de} BIC COBADEFFXXX", [de]), (f"é {gb} Please", [gb]), (f"{packed} EUR 50", [packed]), (f"{packed} 2024-01-01", [packed]), (f"IBAN {no}", [no]), (f"{no} A1.", [no]),
        (f"{de} {packed} {no}", [de, packed, no]), (f"AB12 {de}", [de]), (de, [de]), (f"{de}x", []), (f"x{packed}", []), (packed + "A" * 40, []), ("DE88 3704 0044 0532 0130 00 BIC", []), (None, []),
    ]
    df = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(rows)], "doc_id long, text string")
    for r in pii.find_pii(df).collect():
        text, want = rows[r.doc_id]
        got = [s for s in r.found if s.kind == "iban"]
        assert [s.text for s in got] == want == [text[s.start : s.stop] for s in got], text


@pytest.mark.parametrize("limit", [1_000_000, 0])
def test_secrets_of_ids_with_two_versions(spark, tmp_path, limit):
    one, two, three = "password = abcdefgh1", "x " + "0" * 40, "AKIA" + "B" * 16
    rows = [(1, one), (2, one), (0, two), (1, two), (None, two), (None, three), (None, three), (5, three), (5, three), (6, "AKIA" + "C" * 16), (6, None)]
    n = {None: 0, one: 1, two: 1, three: 1, rows[9][1]: 1}
    df = spark.createDataFrame(rows, "doc_id long, text string")
    blobs = {t: hashlib.sha256((t or "").encode()).digest() for t in n}
    want = sorted((str(i), blobs[t], n[t]) for i, t in rows)

    def got(table, ledger):
        return sorted((str(r.doc_id), bytes(r.blob), len(r.spans)) for r in secrets.scan(table, ledger, secrets.RuleSet("r1"), skip_limit=limit).collect())

    ledger = secrets.BlobLedger(spark, f"file://{tmp_path}/whole")
    assert got(df, ledger) == want and ledger.findings("r1").count() == len(n)
    # a ledger that knows only the first version of id 1 and of null
    ledger = secrets.BlobLedger(spark, f"file://{tmp_path}/grows")
    got(spark.createDataFrame([(1, one), (None, two)], "doc_id long, text string"), ledger)
    assert got(df, ledger) == want and ledger.findings("r1").count() == len(n)


def covered(texts):
    """Bytes of each text in a 200-byte string that starts twice or more."""
    seen = Counter(hash(b[i : i + 200]) for b in texts for i in range(len(b) - 199))
    for b in texts:
        edge = np.zeros(len(b) + 1, int)
        for k in range(len(b) - 199):
            if seen[hash(b[k : k + 200])] > 1:
                edge[k] += 1
                edge[k + 200] -= 1
        yield np.cumsum(edge[:-1]) > 0


@pytest.mark.parametrize("options", [{}, {"group_limit": 2, "bucket": 50}, {"group_limit": 0}])
def test_suffix_dedup(docs, options):
    rows = [(r.doc_id, (r.text or "").encode()) for r in docs.collect()]
    got = {r.doc_id: r for r in suffix_dedup.remove_repeats(docs, **options).collect()}
    for (i, b), gone in zip(rows, covered([b for _, b in rows]), strict=True):
        assert (got[i].n_bytes, got[i].n_removed) == (len(b), gone.sum()), i
        assert got[i].n_spans == (np.diff(np.concatenate([[0], gone.astype(int)])) == 1).sum(), i
        assert got[i].kept_sha256 == hashlib.sha256(np.frombuffer(b, np.uint8)[~gone].tobytes()).hexdigest()


def test_suffix_dedup_of_passages_with_many_edges(spark):
    """One passage in many documents, each with its own text around it."""
    rng = random.Random(2)
    passage = "".join(rng.choice("abcdefgh ") for _ in range(320))
    around = lambda: "".join(rng.choice("ijkl") for _ in range(rng.randrange(60)))
    rows = [(i, around() + passage[rng.randrange(40) :] + around()) for i in range(120)] + [(200, around() * 9), (201, passage * 3), (202, twins()[0]), (203, twins()[1]), (None, passage), (None, passage), (None, "z" * 300)]
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for options in ({}, {"group_limit": 5, "bucket": 8}):
        got = Counter((r.doc_id, r.n_bytes, r.n_removed) for r in suffix_dedup.remove_repeats(df, **options).collect())
        assert got == Counter((i, len(gone), gone.sum()) for (i, _), gone in zip(rows, covered([t.encode() for _, t in rows]), strict=True))


def twins():
    """Two strings of 1024 letters that any polynomial modulo 2^64 confuses."""
    a = "a"
    for _ in range(10):
        a += a.translate(str.maketrans("ab", "ba"))
    return a, a.translate(str.maketrans("ab", "ba"))


def test_hashes_tell_strings_apart_that_repeat_themselves(spark):
    a, b = twins()
    df = spark.createDataFrame([(1, a), (2, b), (3, f"{a} {b}"), (4, f"{b} {a}"), (5, a)], "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in jaccard_join.jaccard_groups(df).collect()}
    assert got == {1: 1, 2: 2, 3: 3, 4: 4, 5: 1}


@pytest.mark.parametrize(("width", "num"), [(4, 85), (5, 80)])
def test_jaccard_join(spark, width, num):
    random.seed(3)
    words, rows = [f"w{i}" for i in range(900)], list(ODD[:5])
    for n in (8, 12, 33, 64, 127, 300):
        base = [random.choice(words) for _ in range(n)]
        for e in (0, 0, 1, 1, 2, max(1, n // 40), max(1, n // 30)):
            x = list(base)
            for _ in range(e):
                x[random.randrange(len(x))] = random.choice(words)
            rows.append((len(rows), " ".join(x)))
    sets = {}
    for i, t in rows:
        w = (t or "").lower().split()
        sets[i] = {tuple(w[k : k + width]) for k in range(max(1, len(w) - width + 1))} if w else set()
    top = {i: i for i in sets}

    def find(x):
        return x if top[x] == x else find(top[x])

    for a in sets:
        for b in sets:
            k = len(sets[a] & sets[b])
            if a < b and k and 100 * k >= num * len(sets[a] | sets[b]):
                p, q = find(a), find(b)
                top[max(p, q)] = min(p, q)
    df = spark.createDataFrame(rows, "doc_id long, text string")
    for r in jaccard_join.jaccard_groups(df, jaccard_join.Plan(width, num, 100)).collect():
        assert (r.component_id, r.n_shingles) == (find(r.doc_id), len(sets[r.doc_id]))


def test_pipeline_with_repeated_and_null_ids(spark):
    import corpus_pipeline

    random.seed(5)
    passage = lambda n: " ".join(random.choice("abcdefgh") * random.randrange(1, 9) + str(random.randrange(999)) for _ in range(n))
    a, b, c, d, e, f = (passage(60) for _ in range(6))
    item, key = passage(20), "password = abcdefgh1"
    rows = [
        *[(1, f"{a} {key}", "x")] * 4, (7, f"{a} {key}", "x"), (None, f"{a} {key}", "x"),  # copies, repeated and without id
        (1, b, "x"), (0, b + " end", "x"), (5, c, "x"), (3, d, "x"), (3, c + " end", "x"),  # ids with two texts
        (None, e, "x"), (None, e, "y"), (None, f"{item} {f}", "x"), (9, f"{f} {item}", "x"), (9, f"AKIA{'A' * 16} {passage(50)}", "x"),
        (2, passage(50), None), (8, None, "x"), (8, "", "x"), (None, None, "x"), (None, None, "x"), (None, None, None),
    ]
    docs = spark.createDataFrame([(i, t, s, None, len(t or "")) for i, t, s in rows], "doc_id long, text string, lang string, source string, n_chars long")
    docs = docs.select("doc_id", "text", "lang", "source", "n_chars")
    order = lambda rs: sorted(map(str, rs))
    sets = [(lambda w: {tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))} if w else set())((t or "").lower().split()) for _, t, _ in rows]
    group = list(range(len(rows)))
    for _ in rows:
        for i, x in enumerate(sets):
            for j, y in enumerate(sets):
                if rows[i] == rows[j] or x and 10 * len(x & y) >= 8 * len(x | y):
                    group[i] = group[j] = min(group[i], group[j])
    least = {}
    for g, r in zip(group, rows, strict=True):
        least[g] = min(least.get(g, r), r, key=lambda r: (r[0] is None, r[0]))
    first = corpus_pipeline.jaccard_join.keep_first(docs, jaccard_join.Plan(5, 80, 100)).cache()
    assert order((r.doc_id, r.text) for r in first.collect()) == order(r[:2] for r in least.values())
    items = spark.createDataFrame([(1, item)], "item_id long, text string")
    clean = decontam.keep_clean(docs, items)
    assert order((r.doc_id, r.text) for r in clean.collect()) == order(r[:2] for r in rows if item not in (r[1] or ""))
    hide = lambda t: t and t.replace(key, "[secret]").replace("AKIA" + "A" * 16, "[secret]")
    done = corpus_pipeline.remove_secrets(spark, docs, "")
    assert order((r.doc_id, r.text) for r in done.collect()) == order((i, hide(t)) for i, t, _ in rows)
    done = corpus_pipeline.remove_secrets(spark, decontam.keep_clean(first, items), "").collect()
    assert order((r.doc_id, r.text) for r in done) == order((i, hide(t)) for i, t, _ in least.values() if item not in (t or ""))


def test_jaccard_links(spark):
    rng = random.Random(8)
    base = [[rng.choice("abcdefghij") * rng.randrange(1, 9) + str(rng.randrange(99)) for _ in range(60)] for _ in range(4)]
    rows = [(None, None), (90, ""), (91, "x y"), (92, "X  y"), (93, "z")]
    for k, words in enumerate(base):
        for e in range(12):
            x = list(words)
            for _ in range(e % 4):
                x[rng.randrange(60)] = "q"
            rows.append((100 * k + e + 1, " ".join(x)))
    rows.append((5, rows[30][1]))  # an id with two texts
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, n string")
    sets = []
    for _, t in rows:
        w = (t or "").lower().split()
        sets.append({tuple(w[k : k + 4]) for k in range(max(1, len(w) - 3))} if w else set())
    near = lambda x, y: bool(x) and 100 * len(x & y) >= 85 * len(x | y)
    want = Counter((rows[i][0], len(x), sum(near(x, y) for j, y in enumerate(sets) if j != i)) for i, x in enumerate(sets))
    for block in (512, 5):
        got, pairs = jaccard_join.jaccard_links(df, block=block)
        assert Counter((r.doc_id, r.n_shingles, r.n_links) for r in got.collect()) == want
        different = {frozenset(x) for x in sets if x}
        assert pairs.count() == sum(near(x, y) for x in different for y in different if x != y) / 2
    both = lambda f: Counter((r.doc_id, r.n_shingles, r.component_id) for r in f.collect())
    assert both(got) == both(jaccard_join.jaccard_groups(df))


def test_tree_loses_no_pair():
    rng = np.random.default_rng(5)
    plan = jaccard_join.Plan()
    v = rng.poisson(0.6, (400, jaccard_join.GROUPS)).astype(np.uint8)
    v[200:] = np.maximum(v[:200].astype(int) + (rng.random((200, jaccard_join.GROUPS)) < 0.03) - (rng.random((200, jaccard_join.GROUPS)) < 0.03), 0)
    n = v.sum(1, dtype=np.int64) + rng.integers(0, 3, 400)
    got = {(min(p), max(p)) for a, b in jaccard_join.rtree_pairs(v, n, plan, 300) for p in zip(a.tolist(), b.tolist(), strict=True)}
    a, b = np.triu_indices(400, 1)
    keep = plan.enough(jaccard_join.overlap_bound(v[a], v[b], n[a], n[b]), n[a], n[b])
    assert got == set(zip(a[keep].tolist(), b[keep].tolist(), strict=True)) and got


def test_embeddings(spark):
    rng = np.random.default_rng(0)
    x = rng.normal(size=(60, 8))
    x = np.concatenate([x, x[:20] + rng.normal(size=(20, 8)) * 0.15, x[:5]])
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(900, None), (901, []), (902, [0.0] * 8), (903, [float("nan")] * 8), (904, [1.0, 2.0]), (905, [2.0, 4.0])]
    df = spark.createDataFrame([(i, v, "x", 1.0) for i, v in rows], "vec_id long, embedding array<double>, rep string, v double")
    got = {r.vec_id: r for r in embed_dedup.near_vectors(df, capacity=16).collect()}
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    hit = u @ u.T >= 0.95
    for i in range(len(x)):
        assert got[i].n_links == hit[i].sum() - 1
    assert got[905].component_id == 904 and got[903].n_links == 0 and len(got) == len(rows)


def test_embeddings_of_ids_with_several_vectors(spark):
    a, b, c, d = [1.0, 0.0, 0.0, 0.0], [0.0, 1.0, 0.0, 0.0], [0.0, 1.0, 0.01, 0.0], [0.0, 0.0, 0.0, 1.0]
    rows = [(1, a), (1, b), (1, b), (2, c), (3, d), (None, d), (None, None), (4, [None, 1.0, 0.0, 0.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = Counter((r.vec_id, r.n_links, r.component_id, r.kept) for r in embed_dedup.near_vectors(df).collect())
    assert got == Counter({(1, 0, 1, True): 1, (1, 2, 1, True): 2, (2, 2, 1, False): 1, (3, 1, 3, True): 1, (None, 1, 3, False): 1, (None, 0, None, True): 1, (4, 0, 4, True): 1})


def pieces_match(rows, texts):
    """Pieces against the tokenizer's own ids; ``texts`` are (id, text) rows."""
    import public_tokenizers as p
    from tokenizers import Tokenizer

    tok = Tokenizer.from_file(p.path("byte_bpe_50k.json"))
    want, seq = Counter(), {}
    for i, t in texts:
        ids = [*tok.encode(t or "", add_special_tokens=False).ids, 0]
        edges = [0, *range(len(ids) % 2048 or 2048, len(ids) + 1, 2048)]
        want.update((i, k, a, b - a, zlib.crc32(np.array(ids[a:b], "<u4").tobytes())) for k, (a, b) in enumerate(zip(edges[:-1], edges[1:], strict=True)))
    assert want == Counter((r.doc_id, r.piece, r.start, r.length, r.ids_crc32) for r in rows)
    for r in rows:
        seq.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for parts in seq.values():
        at = 0
        for offset, length in sorted(parts):
            assert offset == at
            at += length
        assert at <= 2048
    return len(seq)


def test_packing(docs):
    rows = packing.packing_query(docs).collect()
    used = pieces_match(rows, [(r.doc_id, r.text) for r in docs.collect()])
    assert used <= 1.05 * sum(r.length for r in rows) / 2048 + 1


def test_packing_of_odd_texts(spark):
    rng = random.Random(4)
    parts = ["a", "b", "é", " ", "  ", "\n", "\u00a0", "\u2003", "\u3000", "<|endoftext|>", "<|endof", "1", "'s", "!", "Word", "\t", "漢", "\u0085", "\x1c", "𝄞"]
    rows = [(i, "".join(rng.choice(parts) for _ in range(rng.randrange(30)))) for i in range(400)]
    rows += [(500, None), (501, None), (None, "a b"), (None, "a b"), (502, "a<|endoftext|>b"), (503, "<|endoftext|>"), *enumerate(twins(), 504), (506, "x" * 9000)]
    df = spark.createDataFrame([(i, t, 7, "k") for i, t in rows], "doc_id long, text string, length int, key string")
    pieces_match(packing.packing_query(df).collect(), rows)
    pieces = packing.cut_pieces(df, *vocabulary()).withColumnRenamed("key", "doc_id")
    pieces_match(packing.pack(pieces, most=0, key="doc_id").collect(), rows)  # many salts a length


def vocabulary():
    import public_tokenizers as p

    return p.path("byte_bpe_50k.json"), p.PATTERN


def test_packing_constraints():
    for rule in ("norm", "dot"):
        placed = packing.best_fit({5: 7, 3: 9, 1: 4}, tokens=10, documents=2, attention=60, rule=rule)
        load = {}
        for length, _, count, first, _ in placed:
            for b in range(first, first + count):
                load.setdefault(b, []).append(length)
        assert sum(map(len, load.values())) == 20
        assert all(sum(v) <= 10 and len(v) <= 2 and sum(x * x for x in v) <= 60 for v in load.values())


def test_url_rules(spark):
    rows = [(0, None), (1, "x"), (2, "http://EXAMPLE.com/en/a?q"), (3, "http://a.www.example.com/en/"), (4, "http://notexample.com/en/"), (5, "http://x.net"), (6, "ftp://x.net/es/#f"), (7, "http://x.org/f.zip")]
    got = {r.page_id: (r.host, r.path, r.rule, r.verdict) for r in url_filter.filter_urls(spark.createDataFrame(rows, "page_id long, url string"), url_filter.CONTRACT_RULES + url_filter.DEFAULT_RULES).collect()}
    assert got[0] == ("", "", None, "allow") and got[1] == got[0]
    assert got[2] == ("example.com", "/en/a", "example.com/en/", "block")
    assert got[3][2:] == ("www.example.com/en/", "allow") and got[4][2:] == ("com/", "allow")
    assert got[5][2:] == (None, "allow") and got[6][2:] == ("net/es/", "block") and got[7][2:] == (None, "block")


def test_contained_items(spark, docs):
    items = spark.read.parquet(f"{SF}/benchmark.parquet")
    grams = lambda t: (lambda w: {tuple(w[i : i + 5]) for i in range(max(1, len(w) - 4))} if w else set())(re.findall(r"[^\W_]+", (t or "").lower()))
    want = {}
    asked = [(r.item_id, grams(r.text)) for r in items.collect()]
    for r in docs.collect():
        own = grams(r.text)
        want |= {(r.doc_id, i): len(q & own) for i, q in asked if 10 * len(q & own) >= 8 * len(q)}
    assert {(r.doc_id, r.item_id): r.n_shared for r in decontam.contained_items(docs, items).collect()} == want


def test_short_items(spark):
    docs = spark.createDataFrame([(1, "The quick brown fox jumps over it"), (2, "quick Brown"), (3, "quick"), (4, None), (5, "brown quick fox")], "doc_id long, text string")
    items = spark.createDataFrame([(1, "quick brown"), (2, "QUICK"), (3, "fox, jumps: over"), (4, ""), (5, None), (6, "quick brown fox jumps over it"), (7, "jumps fox")], "item_id long, text string")
    got = {(r.doc_id, r.item_id) for r in decontam.contained_items(docs, items).collect()}
    assert got == {(1, 1), (2, 1), (1, 2), (2, 2), (3, 2), (5, 2), (1, 3), (1, 6)}


def test_personal_data_in_context_and_redacted(spark):
    rows = [(1, "the recipient 1.2.3.4"), (2, "IP: 1.2.3.4"), (3, "repay 4111 1111 1111 1111"), (4, "card 4111 1111 1111 1111"), (4, "e-mail a@b.co, a@b.co"), (4, "e-mail a@b.co, a@b.co"), (None, None), (5, "")]
    df = spark.createDataFrame([(i, t, "x") for i, t in rows], "doc_id long, text string, found string")
    score = lambda r: [round(s.score, 4) for s in r.found]
    got = {r.doc_id: score(r) for r in pii.find_pii(df.where("doc_id < 4 or text like 'card%'")).collect()}
    assert got == {1: [0.6], 2: [0.8], 3: [0.7], 4: [0.85]}
    hidden = Counter((r.doc_id, r.text, r.found) for r in pii.redact(df).collect())
    texts = ["the recipient [ip]", "IP: [ip]", "repay [card]", "card [card]", *["e-mail [email], [email]"] * 2, None, ""]
    assert hidden == Counter((i, t, "x") for (i, _), t in zip(rows, texts, strict=True))


def test_models_on_held_out_rows(spark, docs):
    sf = SF.replace("0.001", "0.01")
    real, labels = spark.read.parquet(f"{sf}/documents.parquet"), spark.read.parquet(f"{sf}/labels.parquet")
    q = quality.quality_query(real, labels).where("held_out").join(labels, "doc_id").selectExpr("avg(int(predicted = quality)) AS a").first().a
    lang = langid.language_query(real).where("held_out").join(real.select("doc_id", "lang"), "doc_id").selectExpr("avg(int(lang_pred = lang)) AS a").first().a
    assert q > 0.95 and lang > 0.95
    odd = {r.doc_id: r for r in langid.language_query(docs).collect()}
    assert odd[-1].lang_pred == odd[-2].lang_pred == odd[-9].lang_pred == "und"


def test_scores_match_a_plain_evaluation(spark):
    """Attention and machines with fixed weights, one row at a time."""
    rng = np.random.default_rng(3)
    model = quality.GatedAttention()
    model.constant, model.w["u"] = None, rng.normal(size=24).astype(np.float32)
    rows = [(1, None), (2, ""), (3, "Short text."), (3, "Short text."), (4, "Many words here, 123! " * 90), (None, "x\n" * 3000)]
    df = spark.createDataFrame([(i, t, "a") for i, t in rows], "doc_id long, text string, score string")

    def attention(text):
        body = text.encode()
        cut = [body[k : k + quality.PASSAGE] for k in range(0, len(body), quality.PASSAGE)] or [b""]
        x = np.concatenate([quality.encode(np.frombuffer(c, np.uint8), np.array([0, len(c)]))[0] for c in cut])
        h = np.tanh(np.clip((x - model.center) / model.scale, -8, 8) @ model.w["W"])
        s = (np.tanh(h @ model.w["V"]) / (1 + np.exp(-(h @ model.w["G"])))) @ model.w["a"]
        weight = np.exp(s - s.max()) / np.exp(s - s.max()).sum()
        return 1 / (1 + np.exp(-((weight[:, None] * h).sum(0) @ model.w["u"] + model.w["c"][0])))

    got = sorted((str(r.doc_id), r.score) for r in quality.score_quality(df, model).collect())
    want = sorted((str(i), attention(t or "")) for i, t in rows)
    assert [g[0] for g in got] == [w[0] for w in want] and np.allclose([g[1] for g in got], [w[1] for w in want], atol=1e-5)

    langs = ["en", "de", "fr", "es", "ru"]
    texts = ["the cat and the dog", "der hund und die katze", "le chat et le chien", "el gato y el perro", "кот и собака"]
    x = lambda t: langid.encode(np.frombuffer(t.encode(), np.uint8), np.array([0, len(t.encode())]))[0]
    tree = langid.LanguageTree(np.stack([x(t) for t in texts]), langs)

    def tournament(text):
        v = x(text)
        margin = lambda w: float(v @ w[:-1] + w[-1])
        family = max(range(len(tree.families)), key=lambda k: margin(tree.roots[k]))
        members = tree.members[tree.families[family]]
        if len(members) == 1:
            return members[0]
        (a, b) = members  # two of a family here
        return a if margin(tree.pairs[a, b]) >= 0 else b

    odd = [*texts, "die the der", "una gata", "12 34", None, "", "und", "und"]
    table = spark.createDataFrame([(i, t, "zz") for i, t in enumerate(odd)], "doc_id long, text string, lang string")
    for r in langid.predict_languages(table, tree).collect():
        t = odd[r.doc_id]
        assert r.lang_pred == ("und" if not t or not re.search(r"[^\W\d_]", t) else tournament(t)), t


def test_rows_that_score_are_kept_as_they_are(spark):
    model = quality.GatedAttention()
    model.constant, model.w["u"] = None, np.random.default_rng(3).normal(size=24).astype(np.float32)
    rows = [(i, t, "a", i) for i, t in enumerate([None, "", "Short text.", "Short text.", "Many words here, 123! " * 90, "x\n" * 3000, "!!"])] + [(None, "Short text.", None, None)]
    df = spark.createDataFrame(rows, "doc_id long, text string, label string, score long")
    good = {str(r.doc_id) for r in quality.score_quality(df, model).where("score >= 0.5").collect()}
    kept = quality.keep_good(df, model)
    assert kept.columns == df.columns and Counter(map(str, kept.collect())) == Counter(str(r) for r in df.collect() if str(r.doc_id) in good)
    assert quality.keep_good(df.limit(0), model).count() == 0


def test_repeated_ids_add_no_rows_to_a_fit(spark):
    rows = [(i, ("good words here " if i % 2 else "!!## 00 ") * 20, "en" if i % 2 else "de", "s", i % 2) for i in range(40)]
    docs = spark.createDataFrame([r[:4] for r in rows], "doc_id long, text string, lang string, source string")
    labels = spark.createDataFrame([(r[0], r[4]) for r in rows], "doc_id long, quality int")
    many = docs.crossJoin(spark.range(5)).drop("id").unionAll(docs.selectExpr("null", "text", "lang", "source"))
    once, more = quality.fit_quality(docs, labels), quality.fit_quality(many, labels.unionAll(labels))
    assert all(np.allclose(once.w[k], more.w[k]) for k in once.w)
    a, b = langid.fit_languages(docs), langid.fit_languages(many)
    assert all(np.allclose(p, q) for p, q in zip(a.roots, b.roots, strict=True))


def test_url_table_edges(spark):
    none = spark.createDataFrame([], "page_id long, url string")
    assert url_filter.filter_urls(none, url_filter.CONTRACT_RULES).count() == 0
    rows = [(1, "http://x.net/es/", "h", "p")] * 3 + [(None, None, None, None)]
    got = url_filter.filter_urls(spark.createDataFrame(rows, "page_id long, url string, host string, path string"), url_filter.CONTRACT_RULES).collect()
    assert Counter(tuple(r) for r in got) == Counter({(1, "x.net", "/es/", "net/es/", "block"): 3, (None, "", "", None, "allow"): 1})


def test_a_shared_folder_is_needed_on_a_cluster(spark):
    from types import SimpleNamespace

    from querymend.llm.common import bloom, workspace

    conf = SimpleNamespace(get=lambda *_: None)
    with pytest.raises(ValueError):
        workspace(SimpleNamespace(conf=conf, sparkContext=SimpleNamespace(master="spark://host:7077")))
    keys = spark.range(2000).select(F.col("id").alias("k"))
    made = bloom(keys, "k")
    h = np.array([r[0] for r in spark.range(4000).select(F.xxhash64("id")).collect()]).view(np.uint64)
    assert made.holds(h[:2000]).all() and made.holds(h[2000:]).mean() < 0.2
    assert bloom(keys, "k", 1999) is None


def test_results_do_not_depend_on_the_filters(docs, monkeypatch):
    from querymend.llm import common

    some = docs.where("doc_id < 60")
    rows = lambda: [Counter(map(str, df.collect())) for df in (suffix_dedup.remove_repeats(some), jaccard_join.jaccard_groups(some))]
    filtered = rows()
    monkeypatch.setattr(common.bloom, "__defaults__", (0,))
    assert rows() == filtered


def test_pipeline_runs(spark, tmp_path):
    """All stages on a small table, and on one without rows."""
    import corpus_pipeline

    src = "/root/testdata/sf0.001"
    for rows in (None, 0):
        folder = f"{tmp_path}/{rows}"
        for name in ("documents", "labels", "benchmark"):
            table = spark.read.parquet(f"{src}/{name}.parquet")
            (table if rows is None else table.limit(rows)).write.parquet(f"{folder}/{name}.parquet")
        out = corpus_pipeline.run(spark, folder).collect()
        texts = {r.doc_id for r in spark.read.parquet(f"{folder}/documents.parquet").collect()}
        assert {r.doc_id for r in out} <= texts and (len(out) > 0) == (rows is None)
        assert len({(r.doc_id, r.piece) for r in out}) == len(out)


def test_empty_tables(spark):
    none = spark.createDataFrame([], "doc_id long, text string, lang string")
    empty = spark.createDataFrame([], "doc_id long, quality int")
    assert quality.quality_query(none, empty).count() == 0
    assert langid.language_query(none).count() == 0
    for df in (secrets.secrets_digest(none), suffix_dedup.remove_repeats(none), jaccard_join.jaccard_groups(none), packing.packing_query(none), pii.pii_digest(none), decontam.contained_items(none, spark.createDataFrame([], "item_id long, text string")), embed_dedup.near_vectors(spark.createDataFrame([], "vec_id long, embedding array<float>"))):
        assert df.count() == 0
