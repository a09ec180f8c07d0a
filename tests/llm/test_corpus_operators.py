"""Operators against brute force on fixtures that hold nulls, empty and long texts, ties, repeated rows and clashing columns."""

import random
import re
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest

public_tokenizers = pytest.importorskip("public_tokenizers")
from incwalk.llm import byte_bpe, ngram_join, packing, quality, secrets, substring, token_counts, toxicity, url_filter, vector_search  # noqa: E402

R = random.Random(3)
WORDS = ["alpha", "beta", "Gamma,", "delta", "eps#", "zeta", "eta.", "théta", "iota", "kappa"]
SCHEMA = "doc_id long, text string, lang string, source string, n_chars long, rid long, n_words long, blob string, key string"


def _texts():
    base = [" ".join(R.choice(WORDS) + str(R.randrange(40)) for _ in range(120)) for _ in range(6)]
    out = [None, "", "  \n\t ", "one", "one two three", " ".join(["same"] * 400)]
    for b in base:
        w = b.split()
        out += [b, b]
        for _ in range(4):
            v = list(w)
            for _ in range(R.randrange(1, 6)):
                v[R.randrange(len(v))] = "edit" + str(R.randrange(999))
            out.append(" ".join(v))
        out.append(" ".join(w[:60] + ["tail%d" % R.randrange(9) for _ in range(60)]))
    out.append(" ".join(R.choice(WORDS) for _ in range(30_000)))
    return out


TEXTS = _texts()


@pytest.fixture(scope="module")
def docs(spark):
    rows = [(i, t, "en", "s", 0, 1, 2, "b", "k") for i, t in enumerate(TEXTS)] + [(None, TEXTS[6], None, None, None, None, None, None, None)]
    return spark.createDataFrame(rows, SCHEMA)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def _components(rows, size, num, den):
    sets = [(i, set(ngram_join.shingle_set(t.encode() if t else None, size).tolist())) for i, t in rows]
    parent = list(range(len(sets)))

    def find(a):
        while parent[a] != a:
            a = parent[a]
        return a

    for x in range(len(sets)):
        for y in range(x):
            a, b = sets[x][1], sets[y][1]
            if a and b and den * len(a & b) >= num * len(a | b):
                parent[find(x)] = find(y)
    groups = defaultdict(list)
    for x, (i, _) in enumerate(sets):
        groups[find(x)].append(i)
    least = {g: min((i for i in own if i is not None), default=None) for g, own in groups.items()}
    return Counter((i, len(s), least[find(x)]) for x, (i, s) in enumerate(sets))


@pytest.mark.parametrize(("size", "num"), [(4, 85), (5, 80), (3, 60)])
def test_ngram_join(docs, size, num):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = ngram_join.ngram_jaccard_join(docs, size, num, 100).select("doc_id", "n_shingles", "component_id").collect()
    assert Counter(map(tuple, got)) == _components(rows, size, num, 100)


def test_ngram_join_in_blocks(docs, monkeypatch):
    monkeypatch.setattr(ngram_join, "BLOCK", 150)
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = ngram_join.ngram_jaccard_join(docs, 4, 85, 100).select("doc_id", "n_shingles", "component_id").collect()
    assert Counter(map(tuple, got)) == _components(rows, 4, 85, 100)


def test_pairs_are_verified_once():
    own = random.Random(8)
    base = [own.sample(range(400), 60) for _ in range(6)]
    sets = [sorted({x if own.random() > 0.06 else own.randrange(400) for x in b}) for b in base for _ in range(12)]
    seen = Counter(x for s in sets for x in s)
    shared = [[x for x in s if seen[x] > 1] for s in sets]
    n = np.array([len(s) for s in sets])
    order = [sorted(s, key=lambda x: (seen[x], x)) for s in shared]
    tokens, levels = [np.array(o, np.uint64) for o in order], [np.array([seen[x] for x in o], np.uint16) for o in order]
    block, links, verified = np.array([own.randrange(3) for _ in sets]), [], []
    for i in range(3):
        for j in range(i, 3):
            at = np.flatnonzero((block == i) | (block == j))
            side, own_pairs = (block[at] if i != j else None), []
            links += [(at[a], at[b]) for a, b in ngram_join.link_block(n[at], [tokens[k] for k in at], [levels[k] for k in at], 80, 100, side, own_pairs)]
            verified += [tuple(sorted((int(at[a]), int(at[b])))) for a, b in own_pairs]
    assert verified and max(Counter(verified).values()) == 1

    def groups(pairs):
        lead = list(range(len(sets)))
        for a, b in list(pairs) * len(sets):
            lead[a] = lead[b] = min(lead[a], lead[b])
        return lead

    true = [(a, b) for a in range(len(sets)) for b in range(a) if 100 * len(set(sets[a]) & set(sets[b])) >= 80 * len(set(sets[a]) | set(sets[b]))]
    assert groups(links) == groups(true)


def test_ngram_join_with_hot_keys(docs, monkeypatch):
    monkeypatch.setattr(ngram_join, "CAP", 3)
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    got = ngram_join.ngram_jaccard_join(docs, 4, 85, 100).select("doc_id", "n_shingles", "component_id").collect()
    assert Counter(map(tuple, got)) == _components(rows, 4, 85, 100)


@pytest.mark.parametrize("block", [1_000_000, 150])
def test_ngram_links_are_all_links(docs, empty, monkeypatch, block):
    monkeypatch.setattr(ngram_join, "BLOCK", block)
    members, links = ngram_join.ngram_jaccard_links(docs, 4, 60, 100)
    sets = defaultdict(list)
    for r in docs.collect():
        sets[frozenset(ngram_join.shingle_set(r["text"].encode() if r["text"] else None, 4).tolist())].append(r["doc_id"])
    distinct = [s for s in sets if s]
    linked = Counter()
    for x, a in enumerate(distinct):
        for b in distinct[:x]:
            if 100 * len(a & b) >= 60 * len(a | b):
                linked[a] += 1
                linked[b] += 1
    want = Counter((i, len(s), linked[s]) for s, own in sets.items() for i in own)
    rows = members.collect()
    assert Counter((r["doc_id"], r["n_shingles"], r["n_links"]) for r in rows) == want
    pairs = [tuple(r) for r in links.collect()]
    assert len(pairs) == len(set(pairs)) == sum(linked.values()) // 2 and all(a < b for a, b in pairs)
    assert all((r["class_id"] is None) == (r["n_shingles"] == 0) for r in rows)
    none = ngram_join.ngram_jaccard_links(empty)
    assert none[0].count() == none[1].count() == 0


def test_keep_one_of_each(docs, empty):
    kept = ngram_join.keep_one_of_each(docs, 5, 80, 100)
    assert kept.columns == docs.columns
    want = {c for (_, n, c) in _components([(r["doc_id"], r["text"]) for r in docs.collect()], 5, 80, 100) if n}
    assert {r["doc_id"] for r in kept.where("length(trim(text)) > 2").collect()} == want
    assert ngram_join.keep_one_of_each(empty).count() == 0


def test_substring_dedup(docs, empty):
    rows = [(r["doc_id"], r["text"]) for r in docs.collect()]
    words = [(t or "").encode().split() for _, t in rows]
    seen = Counter(tuple(w[j : j + 35]) for w in words for j in range(len(w) - 34))
    want = Counter()
    for (i, t), w in zip(rows, words, strict=True):
        gone = [False] * len(w)
        for j in range(len(w) - 34):
            if seen[tuple(w[j : j + 35])] > 1:
                gone[j : j + 35] = [True] * 35
        kept = b" ".join(x for x, g in zip(w, gone, strict=True) if not g).decode()
        want[i, len(w), sum(gone), kept if t is not None else None] += 1
    got = substring.substring_dedup(docs, 35)
    assert Counter((r["doc_id"], r["n_words"], r["n_removed"], r["text"]) for r in got.collect()) == want
    assert substring.substring_dedup(empty, 35).count() == 0


def test_token_counts(docs, empty):
    import sentencepiece

    path = public_tokenizers.path("piece_bpe_32k.model")
    model = sentencepiece.SentencePieceProcessor(model_file=path)
    got = token_counts.token_counts(docs, path, 100).collect()
    want = Counter((r["doc_id"], len((r["text"] or "").encode()), len(model.encode(r["text"] or ""))) for r in docs.collect())
    assert Counter((r["doc_id"], r["n_bytes"], r["n_tokens"]) for r in got) == want
    assert all(r["over_limit"] == (r["n_tokens"] > 100) for r in got)
    assert token_counts.token_counts(empty, path).count() == 0


ODD = list("ab  \n\té'sß0123<|>.,世界 Σſ\x1c\x85")
FUZZ = ["".join(R.choice(ODD) for _ in range(R.randrange(40))) for _ in range(3000)] + ["<|endoftext|> x", "A<|ENDOFTEXT|>b, c", "Plain words, here: and CAPITALS too.", "  ", "a ", "x" * 3000]


@pytest.mark.parametrize("name", ["piece_bpe_32k.model", "word_bpe_49k.json", "byte_bpe_50k.json"])
def test_counts_equal_the_library(name):
    path = public_tokenizers.path(name)
    assert token_counts.count_texts(path, FUZZ) == token_counts._counter(path)[0].count(FUZZ)


def test_word_ids_equal_the_library():
    path = public_tokenizers.path("word_bpe_49k.json")
    model = packing._encoder(path)[0]
    want = [np.array(e.ids, "<u4").tobytes() for e in model.encode_batch(FUZZ, add_special_tokens=False)]
    assert packing.word_ids(path, [t.encode() for t in FUZZ]) == want


def test_byte_bpe(docs, spark):
    import tiktoken

    path = public_tokenizers.path("byte_bpe_50k.tiktoken")
    ranks = byte_bpe.load_ranks(path)
    coder = tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=ranks, special_tokens={})
    for r in byte_bpe.encode_documents(docs, path, public_tokenizers.PATTERN).collect():
        text = TEXTS[r["doc_id"]] or "" if r["doc_id"] is not None else TEXTS[6]
        assert r["ids"] == coder.encode_ordinary(text) and r["n_tokens"] == len(r["ids"])
        assert bytes(r["decoded"]) == text.encode()
    for t in ["x" * 60, "é" * 40, "qwertyuiopasdfghjklzxcvbnm" * 4]:
        assert byte_bpe.merge_word(t.encode(), ranks) == coder._core_bpe.encode_single_piece(t.encode())
    some = {b: n for b, n in ranks.items() if n < 3000}  # a small vocabulary: the literal stays small
    small = tiktoken.Encoding("small", pat_str=public_tokenizers.PATTERN, mergeable_ranks=some, special_tokens={})
    words = [" hello", "world", "naïve", "x", "tokenization", None, "x"]
    got = byte_bpe.encode_words(spark.createDataFrame([(w,) for w in words], "word string"), some)
    assert {r["word"]: r["ids"] for r in got.collect()} == {w: small.encode_ordinary(w) for w in words if w}
    assert byte_bpe.encode_documents(docs.limit(0), path, public_tokenizers.PATTERN).count() == 0
    back = byte_bpe.decode_ids(got, some).collect()
    assert all(bytes(r["decoded"]) == r["word"].encode() for r in back)


def test_packing(docs, empty):
    path = public_tokenizers.path("word_bpe_49k.json")
    model = packing._encoder(path)[0]
    rows = packing.pack_documents(docs, path, 256).collect()
    ids = [(r["doc_id"], model.encode(r["text"] or "", add_special_tokens=False).ids + [1]) for r in docs.collect()]
    want = Counter((i, p, a, len(x[a : a + 256]), zlib.crc32(np.array(x[a : a + 256], "<u4").tobytes())) for i, x in ids for p, a in enumerate(range(0, len(x), 256)))
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == want
    bins = defaultdict(list)
    for r in rows:
        bins[r["sequence_id"]].append((r["offset"], r["length"]))
    for own in bins.values():
        at = 0
        for o, n in sorted(own):
            assert o == at
            at += n
        assert at <= 256
    sizes = [r["length"] for r in rows]
    assert -(-sum(sizes) // 256) <= len(bins) <= len(packing.best_fit(sizes, 256))
    assert packing.pack_documents(empty, path).count() == 0


def test_local_search_gains():
    sizes = [R.randrange(1000, 2500) for _ in range(3000)]
    first = packing.best_fit(sizes, 4096)
    last = packing.local_search(sizes, [list(b) for b in first], 4096)
    assert len(last) < len(first) and sorted(i for b in last for i in b) == list(range(3000))
    assert max(sum(sizes[i] for i in b) for b in last) <= 4096


def test_local_search_tries_every_size():
    small = list(range(10, 34))  # 24 documents smaller than the one to give up
    sizes = [*small, 2000, 2100, 616]
    last = packing.local_search(sizes, [list(range(25)), [25], [26]], 2616)  # 2000 for 2100, then 2000 and 616
    assert sorted(i for b in last for i in b) == list(range(27))
    assert [sum(sizes[i] for i in b) for b in last] == [2616, 2616]
    assert packing.give_ups([0, 1, 2], [5, 5, 7]) == [(), (0,), (2,), (0, 2), (0, 1)]


def test_secrets(spark, empty):
    texts = [None, "", "Password = 'abcdefghijkl' x", "secret: token: abcdefghijklmnop", "AKIAABCDEFGHIJKLMN and deadbeefdeadbeef00", "é api_key=" + "a1" * 9, "Password = 'abcdefghijkl' x", "ſecret: token=abcdefghijklmnop", "to\u212aen=abcdefghijklmnop APİ_KEY PASSWD:ABCDEFGHIJKL", "x " * 40_000 + "token=abcdefghijklmnop"]
    df = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")

    def brute(t):
        either = "".join(f"[{c}{c.upper()}]" if c.isalpha() else c for c in "password|passwd|secret|token|api_?key")
        out = [(m.start(), 0, m.end()) for m in re.finditer("(" + either + r""")["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)""", t) if len(m[2]) >= 12]
        out += [(m.start(), 1, m.end()) for m in re.finditer("AKIA[A-Z0-9]+", t) if len(m[0]) >= 18]
        out += [(m.start(), 2, m.end()) for m in re.finditer("[0-9a-f]+", t) if len(m[0]) >= 16]
        return ",".join(f"{secrets.BASE_KINDS[k]}:{a}:{b}" for a, k, b in sorted(out))

    got = {r["doc_id"]: r for r in secrets.secret_findings(df).collect()}
    assert {i: r["base_spans"] for i, r in got.items()} == {i: brute(t or "") for i, t in enumerate(texts)}
    _, ledger = secrets.scan_unseen(df, None, "doc_id")
    _, again = secrets.scan_unseen(df, ledger, "doc_id")
    assert ledger.count() == 8 and again.count() == 0
    red = {r["doc_id"]: r["text"] for r in secrets.redact(df).collect()}
    assert red[0] is None and red[2] == "[secret]' x" and len(red) == len(texts)
    assert secrets.secret_findings(empty).count() == 0
    odd = df.selectExpr("CASE WHEN doc_id <> 2 THEN doc_id END AS doc_id", "text", "'b' AS blob", "'k' AS key", "'s' AS spans", "'x' AS k", "1 AS n_hex")
    rows = secrets.secret_findings(odd).collect()
    assert Counter((r["doc_id"], r["base_spans"]) for r in rows) == Counter((None if i == 2 else i, brute(t or "")) for i, t in enumerate(texts))
    kept = secrets.redact(odd)
    assert kept.columns == odd.columns and Counter((r["blob"], r["spans"], r["n_hex"]) for r in kept.collect()) == {("b", "s", 1): len(texts)}


def test_quality_statistics(docs, spark, empty):
    for r in quality.judge(docs, []).collect():
        t = (TEXTS[r["doc_id"]] if r["doc_id"] is not None else TEXTS[6]) or ""
        w = re.findall(r"[^\x20\x09-\x0D]+", t)
        c, gone = Counter(zip(w, w[1:], w[2:], strict=False)), [0] * len(w)
        for i in range(len(w) - 2):
            if c[tuple(w[i : i + 3])] > 1:
                gone[i : i + 3] = [1] * 3
        lines = [x for x in t.split("\n") if re.search(r"[^\x20\x09-\x0D]", x)]
        assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == (len(w), sum(map(len, w)), sum(x in quality.SYMBOLS for x in t), len(lines) - len(set(lines)), sum(gone))
        assert r["base_failed"] == (len(w) < 50 or 100 * sum(gone) > 50 * len(w)) and r["kept"] == (not r["base_failed"])
    none = spark.createDataFrame([], "doc_id long, quality int")
    assert quality.learn_list(docs, none) == [] and quality.keep_good(empty, []).count() == 0


def test_kept_rows_keep_their_columns(spark):
    good = " ".join(f"w{i}" for i in range(60))
    df = spark.createDataFrame([(1, good, 777, 0.5, "k"), (2, "few words", 778, 0.5, "k"), (3, None, 779, 0.5, "k"), (1, good, 777, 0.5, "k")], "doc_id long, text string, n_words long, repeats double, `__words` string")
    kept = quality.keep_good(df, [])
    assert kept.columns == df.columns and [tuple(r) for r in kept.collect()] == [(1, good, 777, 0.5, "k")] * 2


def test_quality_list_learns(spark):
    rows = [(i, " ".join(["w%d" % R.randrange(500) for _ in range(60)]) + (" ###" * 12 if i % 3 == 0 else "")) for i in range(120)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    labels = spark.createDataFrame([(i, 0 if i % 3 == 0 else 1) for i in range(120)], "doc_id long, quality int")
    got = quality.judge(docs, quality.learn_list(docs, labels)).collect()
    assert sum(r["kept"] != (r["doc_id"] % 3 != 0) for r in got) <= 2


def test_url_filters(spark):
    urls = [None, "nope", "HTTP://WWW.Example.com/en/x?q", "http://a.example.com/en/", "http://x.net/es/a", "http://com", "http://adult-x.example.org/a", "x://y://net/fr/", "http://x.net/es/a"]
    df = spark.createDataFrame(list(enumerate(urls)), "page_id long, url string")
    want = [("", "", None, "block"), ("", "", None, "block"), ("www.example.com", "/en/x", "www.example.com/en/", "allow"), ("a.example.com", "/en/", "example.com/en/", "block"), ("x.net", "/es/a", "net/es/", "block"), ("com", "", None, "allow"), ("adult-x.example.org", "/a", None, "block"), ("y:", "//net/fr/", None, "allow"), ("x.net", "/es/a", "net/es/", "block")]
    many = url_filter.BASE_RULES + url_filter.METHOD_RULES + tuple(url_filter.host_rule("block", f"h{i}.test", "/") for i in range(300))
    for rules in (url_filter.BASE_RULES + url_filter.METHOD_RULES, many):
        got = {r["page_id"]: (r["host"], r["path"], r["rule"], r["verdict"]) for r in url_filter.judge_urls(df, rules).collect()}
        assert [got[i] for i in range(len(urls))] == want
    assert url_filter.judge_urls(df.limit(0)).count() == 0
    odd = df.selectExpr("page_id", "url", "'a' AS address", "'t' AS token", "'n' AS name", "'H' AS Host", "'b' AS base")
    for rules in (url_filter.BASE_RULES + url_filter.METHOD_RULES, many):
        out = url_filter.judge_urls(odd, rules)
        assert out.columns == ["page_id", "url", "address", "token", "name", "base", "host", "path", "rule", "verdict"]
        rows = {r["page_id"]: r for r in out.collect()}
        assert [(r["host"], r["path"], r["rule"], r["verdict"]) for r in (rows[i] for i in range(len(urls)))] == want and all(r["address"] == "a" and r["token"] == "t" for r in rows.values())


def test_filter_lists(spark):
    rules = url_filter.parse_rules("! a comment\n\n||ads.example.org^\n@@||ads.example.org/ok/\n/track/*.gif\nbanner\n-popup.")
    assert [r.tokens for r in rules] == [("ads", "example", "org"), ("ads", "example", "org", "ok"), ("track",), ("banner",), ("popup",)]
    urls = {"http://ads.example.org/x": "block", "http://my.ads.example.org": "block", "http://bads.example.org/": "allow", "http://ads.example.org/ok/1": "allow", "http://x.test/track/a.GIF": "block", "http://x.test/track/a.png": "allow", "http://x.test/Banner.html": "block", "http://x.test/banners": "allow", "http://x.test/a-popup.js": "block"}
    df = spark.createDataFrame(list(urls.items()), "url string, want string")
    no_token = url_filter.UrlRule("free", "zzz[0-9]", (), "block")
    for own in (rules, rules + (no_token,), rules + tuple(url_filter.host_rule("block", f"h{i}.test", "/") for i in range(300))):
        assert {r["url"]: r["verdict"] for r in url_filter.judge_urls(df, own).collect()} == urls
    assert url_filter.judge_urls(spark.createDataFrame([("http://a.b/zzz1",)], "url string"), (no_token,)).first()["verdict"] == "block"


def test_toxicity_tolerates_gaps():
    toxic = ["qw er ty loser as", "idiot zx cv", "what a loser", "you idiot now", "moron here", "a moron there"] * 12
    clean = ["".join(R.choice("aeioustrn") for _ in range(6)) + " " + "".join(R.choice("aeioustrn") for _ in range(5)) for _ in range(150)]
    model = toxicity.train(toxic + clean, [True] * len(toxic) + [False] * len(clean))
    p = lambda w: float(model.probability(model.values([w])[0]))
    assert min(p("loser"), p("lo-ser")) > 0.3 > p("nature")
    assert toxicity.instances("a i d i o t b") == ["a", "i", "d", "i", "o", "t", "b", "aidiotb"]


def _clean_texts():
    own = random.Random(5)
    return ["".join(own.choice("aeioustrn") for _ in range(6)) + " " + "".join(own.choice("aeioustrn") for _ in range(5)) for _ in range(150)] + ["nature walks", "a walk", "it is so"] * 10


GAPPED = ["qw er ty loser as", "idiot zx cv", "what a loser", "you idiot now", "moron here", "a moron there"] * 12


def test_toxicity_gap_in_repeated_letters():
    clean = _clean_texts()
    model = toxicity.train(GAPPED + clean, [True] * len(GAPPED) + [False] * len(clean))
    p = lambda w: float(model.probability(model.values([w])[0]))
    assert min(p("mo.ron"), p("m.oron"), p("id.iot"), p("lo-ser")) > 0.3 > p("nature")


def _subsequence_kernel(a, b):
    """Weighted common subsequences of three letters within the span, straight from the definition."""

    def weights(w):
        out = Counter()
        code = [toxicity._code(c) for c in w]
        for i in range(len(w)):
            for j in range(i + 1, len(w)):
                for k in range(j + 1, len(w)):
                    if k - i < toxicity.SPAN and code[i] and code[j] and code[k]:
                        out[code[i], code[j], code[k]] += toxicity.DECAY ** (k - i - 2)
        return out

    x, y = weights(a), weights(b)
    return sum(v * y[u] for u, v in x.items())


def test_toxicity_kernel_and_machine_by_brute_force():
    words = ["idiot", "id-iot", "i.d.i.o.t", "clown", "naïve", "ab", "moron", "mo0ron", "aaaa"]
    phi = toxicity.dense(words)
    norm = []
    for w in words:
        at = [(i, j, k) for i in range(len(w)) for j in range(i + 1, len(w)) for k in range(j + 1, min(len(w), i + toxicity.SPAN)) if toxicity._code(w[i]) and toxicity._code(w[j]) and toxicity._code(w[k])]
        norm.append(max(sum(toxicity.DECAY ** (2 * (k - i - 2)) for i, _, k in at), 1e-3) ** 0.5)
    for m, a in enumerate(words):
        for n, b in enumerate(words):
            assert phi[m] @ phi[n] == pytest.approx(_subsequence_kernel(a, b) / norm[m] / norm[n], abs=1e-4)
    model = toxicity.train(GAPPED + ["nature walks", "strings attached"] * 20, [True] * len(GAPPED) + [False] * 40)
    assert model.values(words) == pytest.approx(phi @ model.weight + model.bias, abs=1e-3)


def test_toxicity_scores_every_row(spark, docs):
    model = toxicity.train(GAPPED + _clean_texts(), [True] * len(GAPPED) + [False] * len(_clean_texts()))
    texts = [None, "", "  ", "you idiot", "you idiot", "walks " * 30_000 + "idiot", "walks " * 30_000, "i d i o t"]
    df = spark.createDataFrame([(i if i else None, t, 0.5, 1) for i, t in enumerate(texts)], "doc_id long, text string, score double, predicted int")
    got = {r["doc_id"]: r for r in toxicity.score_texts(df, model).collect()}
    for i, t in enumerate(texts):
        bag = toxicity.instances(t)
        want = model.probability(max(model.values(bag)) if bag else model.wordless)
        assert got[i or None]["score"] == pytest.approx(float(want), abs=1e-4)
        assert got[i or None]["held_out"] == (bool(i) and zlib.crc32(str(i).encode()) % 4 == 2)
    assert [got[i or None]["predicted"] for i in range(8)] == [0, 0, 0, 1, 1, 1, 0, 1]


def test_toxicity_rows(docs, empty):
    model = toxicity.train(["a"], [False])
    got = toxicity.score_texts(docs, model).collect()
    assert len(got) == len(TEXTS) + 1 and all(0 <= r["score"] <= 1 and r["predicted"] == 0 for r in got)
    assert toxicity.score_texts(empty, model).count() == 0


def test_vector_search(spark):
    rng = np.random.default_rng(1)
    x = rng.standard_normal((400, 16)).astype(np.float32)
    x[50:60] = x[49]
    rows = [(i, [float(c) for c in v]) for i, v in enumerate(x)] + [(1000, None), (1020, [0.0] * 16), (1040, [float("nan")] + [1.0] * 15), (1060, [1.0])]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    want = vector_search.brute_force(x.astype(float), np.arange(400), 20, 20)
    got = defaultdict(dict)
    for r in vector_search.nearest(df).collect():
        got[r["query_id"]][r["rank"]] = r["vec_id"]
    assert set(got) == set(want) and all(sorted(v) == list(range(1, 21)) for v in got.values())
    assert sum(len(set(got[q].values()) & set(want[q])) for q in want) >= 0.9 * 20 * len(want)
    exact = defaultdict(dict)
    for r in vector_search.nearest(df, share=1.1).collect():
        exact[r["query_id"]][r["rank"]] = r["vec_id"]
    assert {q: [v[k] for k in range(1, 21)] for q, v in exact.items()} == want
    assert vector_search.nearest(df.limit(0)).count() == 0
    again = df.unionByName(df.where("vec_id BETWEEN 20 AND 45")).unionByName(df.where("vec_id = 3").selectExpr("CAST(null AS long) AS vec_id", "embedding"))
    twice = defaultdict(dict)
    for r in vector_search.nearest(again.selectExpr("vec_id", "embedding", "1 AS cls", "2 AS home", "3 AS rank"), share=1.1).collect():
        assert r["rank"] not in twice[r["query_id"]]
        twice[r["query_id"]][r["rank"]] = r["vec_id"]
    assert {q: len(set(v.values())) for q, v in twice.items()} == dict.fromkeys(want, 20)
    few = vector_search.nearest(df.where("vec_id < 4")).collect()
    assert [(r["rank"], r["query_id"]) for r in sorted(few, key=lambda r: r["rank"])] == [(1, 0), (2, 0), (3, 0)]


@pytest.mark.parametrize("n", [12, 15, 25, 100])
def test_vector_search_on_tables_of_few_leaves(spark, n):
    x = np.random.default_rng(n).normal(size=(n, 16)).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>")
    want = vector_search.brute_force(x.astype(float), np.arange(n), 20, 1)
    got = defaultdict(list)
    for r in sorted(vector_search.nearest(df, query_every=1).collect(), key=lambda r: r["rank"]):
        got[r["query_id"]].append(r["vec_id"])
        assert r["score"] == pytest.approx(float(x[r["query_id"]].astype(float) @ x[r["vec_id"]].astype(float)))
    assert all(len(got[q]) == min(20, n - 1) for q in want)
    if n <= 84:
        assert got == want
    assert sum(len(set(got[q]) & set(want[q])) for q in want) >= 0.9 * sum(map(len, want.values()))


@pytest.mark.parametrize("scale", [1e25, 1e150, 1e-150])
def test_vector_search_of_extreme_values(spark, scale):
    x = np.random.default_rng(4).standard_normal((300, 8)) * scale
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    got = defaultdict(list)
    for r in sorted(vector_search.nearest(df).collect(), key=lambda r: r["rank"]):
        got[r["query_id"]].append(r["vec_id"])
    want = vector_search.brute_force(x / scale, np.arange(300), 20, 20)
    assert all(len(got[q]) == 20 for q in want) and sum(len(set(got[q]) & set(want[q])) for q in want) >= 0.9 * 20 * len(want)


def test_vector_search_scores_fewer_rows_than_a_scan(spark):
    rng = np.random.default_rng(6)
    middle = rng.standard_normal((40, 16)) * 4
    x = (middle[rng.integers(40, size=4000)] + rng.standard_normal((4000, 16)) * 0.3).astype(np.float32)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<float>").repartition(4)
    want = vector_search.brute_force(x.astype(float), np.arange(4000), 20, 20)
    for share, candidates, most in ((0.45, None, 0.5), (0.45, 400, 0.15)):
        near, effort = vector_search.search(df, share=share, candidates=candidates)
        got = defaultdict(set)
        for r in near.collect():
            got[r["query_id"]].add(r["vec_id"])
        e = effort.first()
        assert sum(len(got[q] & set(want[q])) for q in want) >= 0.9 * 20 * len(want)
        assert e["scored"] <= most * e["rows"] * e["queries"]


def test_pipeline_stages(spark):
    import corpus_pipeline as cp

    sf = "/root/testdata/sf0.001"
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    before = {r["doc_id"]: r["text"] for r in docs.collect()}
    good = cp.quality_rules(spark, docs, sf)
    assert good.columns == docs.columns
    one = cp.near_duplicates(spark, good, sf)
    rows = [(r["doc_id"], r["text"]) for r in good.collect()]
    assert {r["doc_id"] for r in one.collect()} == {c for (_, n, c) in _components(rows, 5, 80, 100)}
    words = [(r["doc_id"], (r["text"] or "").encode().split()) for r in one.collect()]
    seen = Counter(tuple(w[j : j + 50]) for _, w in words for j in range(len(w) - 49))
    want = {}
    for i, w in words:
        gone = [False] * len(w)
        for j in range(len(w) - 49):
            if seen[tuple(w[j : j + 50])] > 1:
                gone[j : j + 50] = [True] * 50
        want[i] = b" ".join(x for x, g in zip(w, gone, strict=True) if not g).decode()
    less = cp.repeated_passages(spark, one, sf)
    got = {r["doc_id"]: r for r in less.collect()}
    assert less.columns == docs.columns and {i: r["text"] for i, r in got.items()} == want and all(r["n_chars"] == len(r["text"]) for r in got.values())
    safe = {r["doc_id"]: r["text"] for r in cp.secret_scans(spark, less, sf).collect()}
    for i, t in want.items():
        parts, last = [], 0
        for a, b, _ in secrets.scan(t):
            if a >= last:
                parts += [t[last:a], "[secret]"]
            last = max(last, b)
        assert safe[i] == "".join(parts) + t[last:]
    model = packing._encoder(public_tokenizers.path("word_bpe_49k.json"))[0]
    rows = cp.run(spark, sf).collect()
    ids = {i: model.encode(t or "", add_special_tokens=False).ids + [1] for i, t in safe.items()}
    assert Counter((r["doc_id"], r["start"], r["length"], r["ids_crc32"]) for r in rows) == Counter((i, a, len(x[a : a + 4096]), zlib.crc32(np.array(x[a : a + 4096], "<u4").tobytes())) for i, x in ids.items() for a in range(0, len(x), 4096))
    assert {r["doc_id"] for r in rows} <= set(before)


def test_pipeline_stages_on_odd_tables(spark):
    import corpus_pipeline as cp

    sf = "/root/testdata/sf0.001"
    schema = "doc_id long, text string, lang string, source string, n_chars long"
    long = " ".join(f"w{i}" for i in range(30_000))
    odd = spark.createDataFrame([(1, None, "en", "s", None), (2, "", None, None, 0), (3, long, "en", "s", 1), (3, long, "en", "s", 1), (None, " ".join(f"v{i}" for i in range(80)), "en", "s", 1), (5, "token=abcdefghijklmnop " + long[:900], "en", "s", 1)], schema)
    for name, stage in cp.STAGES:
        assert stage(spark, odd.limit(0), sf).count() == 0, name
        out = stage(spark, odd, sf)
        assert len(out.collect()) > 0, name
        if name != "sequence_packing":
            assert out.columns == odd.columns
    kept = {r["doc_id"] for r in cp.quality_rules(spark, odd, sf).collect()}
    assert not kept & {1, 2}
    assert [r["doc_id"] for r in cp.near_duplicates(spark, odd, sf).collect()].count(3) == 1
    assert "[secret]" in {r["doc_id"]: r["text"] for r in cp.secret_scans(spark, odd, sf).collect()}[5]
    assert cp.sequence_packing(spark, odd, sf).where("doc_id = 1").first()["length"] == 1
