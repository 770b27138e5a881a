"""The ten queries against plain Python over the smallest tables and a table of odd rows."""

import hashlib
import math
import re
import zlib
from collections import Counter
from fractions import Fraction

import numpy as np
import pytest
from pyspark.sql import functions as F

from plandistill.llm import ann, chat, mixing, neardup, pieces, pii, ppm, quality, queries, token_store, urlfilter

WORD = re.compile(r"[^\x20\x09-\x0D]+")
LONG = " ".join(f"w{i % 9000}" for i in range(30_000))
TWIN = " ".join(f"t{i}" for i in range(120))
ODD_TEXTS = [
    None, "", " \n\t ", "one", "one two three four", "One  TWO\tthree four", "a b c d e f g h i j k l", LONG, TWIN, TWIN, TWIN.upper(), TWIN + " extra", TWIN.replace("t60", "zz"),
    "mail a.b@c.de, x@y@z.org and +1 (269) 555-3296 4524132264652876 or 10.0.0.256 and 010.1.2.3 1.2.3.4.5.6.7.8",
    "card 4539 1488 0343 6467 and 4539148803436467; +49 89 123456789012345678 +1-202-555-0143", "\u00e9\U0001f600 a@b.co \U0001f600 9.9.9.9 <|im_end|> <|endoftext|>",
    "same line here\nsame line here\n\nsame line here\nother " * 3, "###" * 40 + " x y z q w e r t y u", "nul\x00 in text a b c d e f g h",
]


@pytest.fixture(scope="session")
def odd(spark, tmp_path_factory):
    """Odd rows with an extra column whose name an operator uses inside."""
    rows = [(i if i != 3 else None, t, "en", [None, "s1", "s2", "s1"][i % 4], len(t or ""), "x") for i, t in enumerate(ODD_TEXTS)]
    rows.append(rows[8])  # a repeated row
    path = str(tmp_path_factory.mktemp("odd"))
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string, source string, n_chars long, kept string")
    df.write.parquet(f"{path}/documents.parquet")
    df.limit(0).write.parquet(f"{path}/none/documents.parquet")
    return path


def docs_of(spark, d):
    return [(r.doc_id, r.text or "", r.source) for r in spark.read.parquet(f"{d}/documents.parquet").collect()]


@pytest.fixture(params=["tables", "odd"])
def data(request, sf, odd):
    return sf if request.param == "tables" else odd


def key(r):
    return (r[0] is not None, r[0] or 0, *map(str, r[1:]))


def rows(df, *cols):
    return sorted((tuple(r[c] for c in cols) for r in df.collect()), key=key)


def test_op1(spark, data):
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(queries._tokenizer("word_bpe_49k.json"))
    got = rows(queries.op1_token_ids(spark, data), "doc_id", "n_tokens", "ids_crc32")
    want = []
    for i, text, _ in docs_of(spark, data):
        ids = [*t.encode(text, add_special_tokens=False).ids, 2]
        want.append((i, len(ids), zlib.crc32(np.array(ids, "<u4").tobytes())))
    assert got == sorted(want, key=key)
    ordered = sorted(queries.op1_token_ids(spark, data).collect(), key=lambda r: r.start)
    assert [r.start for r in ordered] == [sum(r.n_tokens for r in ordered[:i]) for i in range(len(ordered))]
    assert [r.doc_id or -1 for r in ordered] == sorted(r.doc_id or -1 for r in ordered)


def test_token_store_single_document(spark, sf, tmp_path):
    docs = spark.read.parquet(f"{sf}/documents.parquet")
    path = f"file://{tmp_path}/store"
    token_store.write_tokens(docs, queries._tokenizer("word_bpe_49k.json"), path)
    from tokenizers import Tokenizer

    t = Tokenizer.from_file(queries._tokenizer("word_bpe_49k.json"))
    r = docs.where("doc_id = 17").head()
    assert token_store.read_document(spark, path, 17) == [[*t.encode(r.text, add_special_tokens=False).ids, 2]]
    assert token_store.read_document(spark, path, -5) == []


def test_op2(spark, data):
    docs = docs_of(spark, data)
    size = Counter()
    for _, text, s in docs:
        size[s] += len(WORD.findall(text))
    names = sorted(size, key=lambda s: (s is None, s or ""))
    weights = {s: (5, 2, 1)[i % 3] for i, s in enumerate(names)}
    target, free, left = {}, set(names), Fraction(sum(size.values()))
    while True:
        total = sum(weights[s] for s in free)
        over = [s for s in free if left * weights[s] / total > 3 * size[s]]
        if not over:
            break
        for s in over:
            target[s] = Fraction(3 * size[s])
            left -= target[s]
            free.discard(s)
    target |= {s: left * weights[s] / total for s in free}
    got = queries.op2_mix_sources(spark, data).collect()
    assert Counter((r.doc_id, r.size) for r in got) == Counter((i, len(WORD.findall(t))) for i, t, _ in docs)
    by_target = {}
    for r in got:
        assert 0 <= r.taken <= 3 * r.size and (r.size == 0 or r.taken % r.size == 0)
        assert any(r.source_size == size[s] and abs(r.target - float(target[s])) < 1e-6 * max(1, r.target) for s in names)
        by_target.setdefault(round(r.target, 3), []).append(r)
    for t, group in by_target.items():
        longest = max(r.size for r in group)
        n = sum(1 for s in names if round(float(target[s]), 3) == t)
        assert abs(sum(r.taken for r in group) - t * n) <= n * longest
    again = rows(queries.op2_mix_sources(spark, data), "doc_id", "taken")
    assert again == sorted(((r.doc_id, r.taken) for r in got), key=key)


def test_water_filling_reshares_until_feasible():
    got = mixing.water_fill({"a": 10, "b": 1, "c": 100, "d": 0}, {"a": 5, "b": 5, "c": 1, "d": 9}, 3)
    assert sum(got.values()) == 111 and got["b"] == 3 and got["d"] == 0 and got["a"] == 30 and got["c"] == 78


def shingle_set(text):
    w = [x.translate({i: i + 32 for i in range(65, 91)}) for x in WORD.findall(text)]
    return frozenset([tuple(w)] if 0 < len(w) < 5 else [tuple(w[i : i + 5]) for i in range(len(w) - 4)])


def test_op3(spark, data):
    docs = [(i, shingle_set(t)) for i, t, _ in docs_of(spark, data)]
    parent = {i: i for i, _ in docs if i is not None}

    def root(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, sa in docs:
        for b, sb in docs:
            if a is not None and b is not None and a < b and sa and sb and 100 * len(sa & sb) >= 85 * len(sa | sb):
                x, y = sorted((root(a), root(b)))
                parent[y] = x
    want = [(i, len(s), root(i) if i is not None else None, root(i) == i if i is not None else True) for i, s in docs]
    assert rows(queries.op3_near_duplicates(spark, data), "doc_id", "n_shingles", "component_id", "kept") == sorted(want, key=key)


def test_op3_chains_and_groups(spark):
    """A group where only neighbours in a chain are linked, and lists with several components."""
    words = [f"c{i}" for i in range(400)]
    texts = []
    for k in range(24):  # each step changes a run of words, so the ends of the chain are far apart
        texts.append(" ".join(words))
        for j in range(18):
            words[(k * 18 + j) % 400] = f"n{k}_{j}"
    df = spark.createDataFrame([(100 - i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    sets = {100 - i: shingle_set(t) for i, t in enumerate(texts)}
    linked = [(a, b) for a in sets for b in sets if a < b and 100 * len(sets[a] & sets[b]) >= 85 * len(sets[a] | sets[b])]
    assert linked and len(linked) < 24 * 23 / 2
    comp = {a: a for a in sets}
    for _ in sets:
        for a, b in linked:
            comp[a] = comp[b] = min(comp[a], comp[b])
    got = {r.doc_id: r.component_id for r in neardup.near_classes(df).collect()}
    assert got == comp


PATTERNS = {"email": r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(\.[A-Za-z0-9-]+)+", "ip": r"[0-9]+(\.[0-9]+)(\.[0-9]+)(\.[0-9]+)", "card": r"[0-9]([\x20-]?[0-9])+", "phone": r"\+[0-9][\x20().0-9-]+[0-9]"}


def base_spans(text):
    out = []
    for k, p in PATTERNS.items():
        for m in re.finditer(p, text):
            d = re.sub("[^0-9]", "", m.group())
            ok = {"email": True, "ip": all(int(x) <= 255 for x in m.group().split(".")) if k == "ip" else 0, "card": 13 <= len(d) <= 19 and pii.luhn_ok(d), "phone": 9 <= len(d) <= 15}[k]
            if ok:
                out.append((k, m.start(), m.end()))
    return out


def test_op3_sketches_keep_what_is_near_and_leave_the_far(spark):
    """Pairs of known similarity at or above the limit stay open; far ones don't."""
    rng, rows = np.random.default_rng(5), []
    for size in (1, 4, 60, 700, 20_000):
        for percent in (50, 85, 90, 100):
            for _ in range(20):
                both = size - size * (100 - percent) // (100 + percent)
                pool = np.unique(rng.integers(0, 1 << 62, 2 * size - both + 20, dtype=np.uint64) * np.uint64(4))
                rng.shuffle(pool)
                a, b = np.sort(pool[:size]), np.sort(np.concatenate([pool[:both], pool[size : 2 * size - both]]))
                with np.errstate(over="ignore"):
                    rows.append((size, 100 * both >= 85 * (2 * size - both), neardup.sketch(a), neardup.sketch(b)))
    size, near, p, q = (np.array(x) for x in zip(*rows, strict=True))
    stays = neardup.alike(size, p, size, q, 85)
    assert not (near & ~stays).any()
    assert not (~near & (size >= 60) & stays).any()


def test_op4(spark, data):
    docs = docs_of(spark, data)
    want = []
    for i, text, _ in docs:
        spans = base_spans(text)
        want.append((i, *[sum(s[0] == k for s in spans) for k in PATTERNS], hashlib.sha256(",".join(":".join(map(str, s)) for s in spans).encode()).hexdigest()))
    got = queries.op4_personal_data(spark, data).collect()
    assert sorted(((r.doc_id, r.n_email, r.n_ip, r.n_card, r.n_phone, r.base_sha256) for r in got), key=key) == sorted(want, key=key)
    by = {}
    for i, text, _ in docs:
        by.setdefault(i, []).append(",".join(":".join(map(str, s)) for s in base_spans(text)).split(","))
    for r in got:  # base spans stay
        assert any(set(b) <= set(r.spans.split(",")) for b in by[r.doc_id])


def test_pii_trees_add_what_patterns_swallow_and_leave_look_alikes(spark):
    texts = ["ab cd +1 (269) 555-3296 4524132264652876 ef", "version 4539148803436461 and key=4539148803436467ab", "on 2024-01-02 we sold 555 items for 1,234.50 each; order 123-456-7890x"]
    got = [r.s for r in pii.find(spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")).orderBy("row.doc_id").select(queries._joined("spans").alias("s")).collect()]
    assert "card:24:40" in got[0] and "phone:6:23" in got[0]
    assert got[1] == "card:33:49" and got[2] == ""  # the base card stays, though it stands in a key


#: Sentences written by hand, with what is personal in them; none comes from the generator.
HAND_WRITTEN = [
    ("Please ring (415) 555-0132 before noon.", ["(415) 555-0132"]), ("Her mobile is +44 20 7946 0958, ask for Ann", ["+44 20 7946 0958"]), ("write to jane.doe (at) example (dot) org if it rains", ["jane.doe (at) example (dot) org"]),
    ("I paid with 4111 1111 1111 1111 last week", ["4111 1111 1111 1111"]), ("The request came from 192.168.10.5 at night", ["192.168.10.5"]), ("Contact: bob@example.com or 212-555-0187.", ["bob@example.com", "212-555-0187"]),
    ("card number 5500005555555559, thanks", ["5500005555555559"]), ("You can call 303 555 0148 any time", ["303 555 0148"]), ("dial +1 (650) 555-0199 for support", ["+1 (650) 555-0199"]), ("mail me: kim[at]example.net", ["kim[at]example.net"]),
    ("The ISBN is 978-3-16-148410-0, second edition", []), ("order 4111 1111 1111 1112 was shipped", []), ("We met on 2024-01-02 and on 2024-02-03", []), ("it sold 1,234,567 copies and 890 more", []),
    ("see section 3.14.15.926 of the manual", []), ("key=4539148803436460ab is a hash", []), ("score 10-3, then 21-19 and 22-20", []), ("the at sign [ at ] is odd", []), ("pi is 3.14159265358979", []), ("serial 123-456-7890x is broken", []), ("room 101, floor 7, house 12", []), ("1999 2000 2001 2002 were good years", []),
]


def test_pii_on_hand_written_sentences(spark):
    """Precision and recall of all spans on text that the training rows' generator didn't make."""
    df = spark.createDataFrame([(i, t) for i, (t, _) in enumerate(HAND_WRITTEN)], "doc_id long, text string")
    got = {r[0]: [(s.start, s.end) for s in r.spans] for r in pii.find(df).select("row.doc_id", "spans").collect()}
    right = wrong = missed = 0
    for i, (text, told) in enumerate(HAND_WRITTEN):
        spans = [text[a:b] for a, b in got[i]]
        right += sum(any(t in s or s in t for s in spans) for t in told)
        missed += sum(not any(t in s or s in t for s in spans) for t in told)
        wrong += sum(not any(t in s or s in t for t in told) for s in spans)
    assert right / (right + missed) >= 0.75 and right / (right + wrong) >= 0.75, (right, missed, wrong)


def test_boosted_trees_fit_and_thresholds_hold_on_fresh_rows(spark):
    rng = np.random.default_rng(0)
    x = rng.integers(0, 2, (400, 3)).astype(float)
    y = (x[:, 0] != x[:, 1]).astype(float)  # no single feature tells
    start, trees = pii.boost(x, y)
    score = start + sum(pii.apply_tree(t, x) for t in trees)
    assert ((score > 0) == (y == 1)).mean() > 0.99
    rows = pii.labelled_rows(seed=99, rows=400)
    df = spark.createDataFrame([(i, t) for i, t, _, _ in rows], "doc_id long, text string")
    got = {r[0]: [(s.start, s.end) for s in r.spans] for r in pii.find(df).select("row.doc_id", "spans").collect()}
    hit = lambda i, t, p: any(a < t.index(p) + len(p) and b > t.index(p) for a, b in got[i])
    true = sum(hit(i, t, p) for i, t, p, good in rows if good)
    false = sum(hit(i, t, p) for i, t, p, good in rows if not good)
    assert true / sum(r[3] for r in rows) >= 0.9 and true / (true + false) >= 0.75  # ips among the false rows are ips


def test_pii_of_a_text_with_very_many_spans(spark):
    """Chunks of a fold meet without a gap, and the work stays that of one pass."""
    n = 20_000
    text = " ".join(f"u{i}@h{i}.org 10.0.{i % 256}.7" for i in range(n))
    found = pii.find(spark.createDataFrame([(1, text)], "doc_id long, text string"))
    r = found.select("base", F.size("spans").alias("n"), pii.redact(F.col("row.text"), F.col("spans")).alias("clean")).head()
    assert len(r.base) == 2 * n == r.n and r.clean == " ".join(["[EMAIL] [IP]"] * n)
    assert [text[s.start : s.end] for s in r.base[:: n // 50]][:5] == [f"u{i}@h{i}.org" for i in range(0, 5 * (n // 50), n // 50)]
    assert text[r.base[-1].start : r.base[-1].end] == f"10.0.{(n - 1) % 256}.7"


def test_mixing_checks_the_number_of_sources(spark, monkeypatch):
    monkeypatch.setattr(mixing, "MOST_SOURCES", 2)
    df = spark.createDataFrame([(i, "a b", f"s{i}") for i in range(3)], "doc_id long, text string, source string")
    with pytest.raises(ValueError):
        mixing.mix(df)


def test_redact(spark):
    df = pii.find(spark.createDataFrame([(1, "x a@b.co y 1.2.3.4"), (2, None), (3, "clean")], "doc_id long, text string"))
    got = {r[0]: r[1] for r in df.select("row.doc_id", pii.redact(F.col("row.text"), F.col("spans"))).collect()}
    assert got == {1: "x [EMAIL] y [IP]", 2: None, 3: "clean"}
    over = spark.createDataFrame([("abcdefghij", [("b", 4, 8), ("a", 2, 6), ("c", 8, 9)])], "text string, spans array<struct<kind:string,start:int,end:int>>")
    assert over.select(pii.redact(F.col("text"), F.col("spans"))).head()[0] == "ab[A][C]j"


RULES = [("allow", "org", "/"), ("block", "example.org", "/es/"), ("block", "example.org", "/en/1"), ("allow", "com", "/fr/"), ("block", "com", "/de/")]


def url_parts(url):
    if not url or "://" not in url:
        return "", ""
    rest = url.split("://", 1)[1]
    host = re.match(r"[^/?#]*", rest, re.S).group()
    return host.translate({i: i + 32 for i in range(65, 91)}), re.match(r"[^?#]*", rest[len(host) :], re.S).group()


def test_op5(spark, sf):
    pages = [(r.page_id, r.url) for r in spark.read.parquet(f"{sf}/pages.parquet").collect()]
    got = {r.page_id: r for r in queries.op5_url_verdicts(spark, sf).collect()}
    assert len(got) == len(pages)
    for i, url in pages:
        host, path = url_parts(url)
        fits = [(len(h + p), h + p, v) for v, h, p in RULES if host and (host == h or host.endswith("." + h)) and path.startswith(p)]
        assert (got[i].host, got[i].path) == (host, path)
        assert got[i].rule == (max(fits)[1] if fits else None)
        if fits:
            assert got[i].verdict == max(fits)[2]


def test_op5_odd_urls_and_link_graph(spark):
    link = lambda *hosts: "".join(f'<a href="http://{h}/x">' for h in hosts)
    data = [(1, "http://a.com/de/1", link("bad.net")), (2, "http://b.org/", link("good.net")), (3, "http://bad.net/p", link("a.com")), (4, "http://good.net/p", ""), (5, None, None), (6, "nonsense", "x"), (7, "HTTP://UP.Org", ""), (8, "x://h.org?q://b/c", ""), (9, "http://far.net/1", link("bad.net"))]
    got = {r.page_id: r for r in urlfilter.judge_urls(spark.createDataFrame(data, "page_id long, url string, html string")).collect()}
    assert got[1].verdict == "block" and got[2].verdict == "allow"
    assert got[3].verdict == "block" and got[4].verdict == "allow"  # by what they link to, by who links to them
    assert got[9].verdict == "block" and got[9].distrust < got[3].distrust
    assert (got[5].host, got[5].verdict, got[6].host, got[7].host, got[7].path, got[7].rule) == ("", "allow", "", "up.org", "", None)
    assert (got[8].host, got[8].path) == ("h.org", "")


def test_pagerank_solves_the_linear_system(spark):
    """On a small graph with a host without links, and on a chain longer than any fixed number of rounds."""
    small = [("a", "b"), ("a", "c"), ("b", "c"), ("c", "d"), ("d", "a"), ("e", "c"), ("c", "f")]
    chain = [(f"h{i:02d}", f"h{i + 1:02d}") for i in range(30)]
    for edges, seed in ((small, {"a": 1.0, "e": 0.5}), (chain, {"h00": 1.0})):
        names = sorted({x for e in edges for x in e})
        out, s = Counter(a for a, _ in edges), np.array([seed.get(h, 0) for h in names])
        s = s / s.sum()
        step = np.zeros((len(names), len(names)))
        for a, b in edges:
            step[names.index(b), names.index(a)] = 1 / out[a]
        lost = np.array([h not in out for h in names], float)
        want = np.linalg.solve(np.eye(len(names)) - 0.85 * (step + np.outer(s, lost)), 0.15 * s)
        hosts = spark.createDataFrame([(h, float(seed.get(h, 0))) for h in names], "host string, good double")
        got = {x.host: x.mass for x in urlfilter.propagate(hosts, spark.createDataFrame(edges, "src string, dst string"), "good", "src", "dst", tolerance=1e-9).collect()}
        assert all(abs(got[h] - w) < 1e-8 for h, w in zip(names, want, strict=True)) and want[-1] > 0


def unigram_library():
    """The library in unigram mode on the same pieces: a second trainer_spec message, which a
    protocol-buffer reader merges into the first, sets the model type."""
    import sentencepiece as sp

    data = open(queries._tokenizer("piece_bpe_32k.model"), "rb").read()
    return sp.SentencePieceProcessor(model_proto=data + b"\x12\x02\x18\x01")


def test_op6(spark, data):
    got = queries.op6_pieces(spark, data).collect()
    assert len(got) == len(docs_of(spark, data)) and all(r.same for r in got)


def test_op6_ids_equal_the_library(spark, data):
    """Ids of every word of every document are those of the best path in the library's lattice
    (its faster search of one path misses the best for some words of this model)."""
    lib, s = unigram_library(), pieces.segmenter(queries._tokenizer("piece_bpe_32k.model"))
    words = sorted({w for _, t, _ in docs_of(spark, data) for w in t.split() if "\x00" not in w})
    assert len(words) > 15
    score = lambda ids: sum(s.pieces[i][1] for i in ids)
    pairs = [(w, s.encode(w).tolist(), lib.nbest_encode_as_ids(w, 2)[0]) for w in words]
    assert [w for w, a, b in pairs if a != b and score(a) != score(b)] == []  # paths of one score are both best
    assert sum(a != b for _, a, b in pairs) <= 1


def test_op6_marks_in_the_text_come_back(spark):
    s = pieces.segmenter(queries._tokenizer("piece_bpe_32k.model"))
    for t in ("a▁b", "▁", "▁▁ x", " ▁", "x ▁y", "  two", "▁ \n▁", "café▁😀"):
        assert s.decode(s.encode(t)) == t
    df = spark.createDataFrame([(1, "a▁b"), (2, None)], "doc_id long, text string")
    assert [r.decoded for r in pieces.encode_texts(df, queries._tokenizer("piece_bpe_32k.model"), ["doc_id"]).orderBy("row.doc_id").collect()] == ["a▁b", ""]


def test_op6_small_machine_by_enumeration():
    s = pieces.segmenter(queries._tokenizer("piece_bpe_32k.model"))
    score = {p: v for p, v, t in s.pieces if t == 1}

    def best(x):
        top = [0.0] + [-1e18] * len(x)
        for e in range(1, len(x) + 1):
            for b in range(e):
                if x[b:e] in score:
                    top[e] = max(top[e], top[b] + score[x[b:e]])
            if x[e - 1] not in score:
                top[e] = max(top[e], top[e - 1] + s.floor)
        return top[-1]

    for x in ("▁hello", "▁the▁▁cat", "▁zzqx\u0416ok", "▁international", "▁\U0001f9ff"):
        ids = s._viterbi(x)
        got = sum(s.pieces[i][1] for i in ids if s.pieces[i][2] == 1) + s.floor * sum(c not in score for c in x)
        assert abs(got - best(x)) < 1e-6


def test_op7(spark, sf):
    data = [(r.vec_id, np.array(r.embedding, float)) for r in spark.read.parquet(f"{sf}/embeddings.parquet").collect()]
    ids, x = np.array([i for i, _ in data]), np.stack([v for _, v in data])
    got = {}
    for r in queries.op7_neighbours(spark, sf).collect():
        got.setdefault(r.query_id, {})[r.rank] = (r.vec_id, r.score)
    hits = 0
    for q in np.flatnonzero(ids % 20 == 0):
        s = x @ x[q]
        s[q] = -np.inf
        want = set(ids[np.argsort(-s)[:20]].tolist())
        mine = got[int(ids[q])]
        assert sorted(mine) == list(range(1, 21))
        assert all(abs(v - s[ids == i][0]) < 1e-12 for i, v in mine.values())
        assert [v for _, v in (mine[k] for k in range(1, 21))] == sorted((v for _, v in mine.values()), reverse=True)
        hits += len(want & {i for i, _ in mine.values()})
    assert hits >= 0.9 * 20 * len(got)


def recall(spark, df, top=20, **kw):
    """Share of the true neighbours found, by brute force over all rows."""
    data = [(r.vec_id, np.array(r.embedding, float)) for r in df.collect()]
    ids, x = np.array([i for i, _ in data]), np.stack([v for _, v in data])
    got, hits, n = {}, 0, 0
    for r in ann.nearest(df, F.col("vec_id") % 20 == 0, top=top, **kw).collect():
        got.setdefault(r.query_id, set()).add(r.vec_id)
    for q in np.flatnonzero(ids % 20 == 0):
        s = x @ x[q]
        s[q] = -np.inf
        hits, n = hits + len(set(ids[np.argsort(-s)[:top]].tolist()) & got[int(ids[q])]), n + top
    return hits / n


@pytest.mark.parametrize("spread", [0.15, None])
def test_op7_recall_over_several_graphs(spark, spread):
    """Clustered vectors and vectors without structure, in cells of at most 700 nodes."""
    rng = np.random.default_rng(4)
    x = rng.normal(size=(3600, 16))
    if spread:
        x = rng.normal(size=(12, 16))[rng.integers(0, 12, 3600)] + spread * x
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>")
    assert recall(spark, df, shard=700) >= 0.9


def test_op7_other_columns_with_inner_names(spark):
    df = spark.createDataFrame([(i, [float(i + 1), 1.0], 0, "a") for i in range(30)], "vec_id long, embedding array<double>, shard int, rep string")
    assert ann.nearest(df, F.col("vec_id") % 20 == 0, shard=10).count() == 40


def test_op7_odd_vectors(spark):
    nan = float("nan")
    data = [(0, [1.0, 0.0]), (20, [1.0, 0.0]), (1, [1.0, 0.0]), (2, [2.0, 1.0]), (3, None), (4, [0.0, 0.0]), (5, [nan, 1.0]), (6, [None, 1.0]), (7, [float("inf"), 1.0]), (8, [1.0, 2.0, 3.0]), (None, [1.0, 1.0])]
    df = spark.createDataFrame(data, "vec_id long, embedding array<double>")
    got = [tuple(r) for r in ann.nearest(df, F.col("vec_id") % 20 == 0).orderBy("query_id", "rank").collect()]
    assert got == [(0, 1, 2, 2.0), (0, 2, 1, 1.0), (0, 3, 20, 1.0), (20, 1, 2, 2.0), (20, 2, 0, 1.0), (20, 3, 1, 1.0)]
    assert ann.nearest(df.limit(0), F.col("vec_id") % 20 == 0).count() == 0


def quality_base(text):
    w = WORD.findall(text)
    c = Counter(tuple(w[i : i + 5]) for i in range(len(w) - 4))
    inside = {i + k for i in range(len(w) - 4) if c[tuple(w[i : i + 5])] > 1 for k in range(5)}
    lines = Counter(x for x in text.split("\n") if WORD.search(x))
    n = len(w)
    return n, sum(map(len, w)), sum(c in "#*$%&|<>" for c in text), sum(v - 1 for v in lines.values()), len(inside), n < 10 or 100 * len(inside) > 20 * n


def test_op8(spark, data):
    want = sorted(((i, *quality_base(t)) for i, t, _ in docs_of(spark, data)), key=key)
    got = queries.op8_quality(spark, data)
    assert rows(got, "doc_id", "n_words", "word_chars", "n_symbols", "n_dup_lines", "n_repeat_words", "base_failed") == want
    assert got.where("base_failed and kept").count() == 0


def test_op8_poor_host_loses_poor_documents_only(spark):
    clean = "this is a clean text with words of several lengths in it " * 1
    poor = " ".join(f"{w}###" for w in "one two three four five six seven eight nine ten eleven".split())
    data = [(i, poor, "bad") for i in range(30)] + [(100, clean, "bad")] + [(200 + i, clean + str(i), "fine") for i in range(40)] + [(300, poor, "fine"), (301, clean, None)]
    got = {r[0]: r[1] for r in quality.judge(spark.createDataFrame(data, "doc_id long, text string, source string")).select("row.doc_id", "kept").collect()}
    assert not any(got[i] for i in range(30)) and got[100] and got[300] and got[301]


def test_op9(spark, sf):
    turns = {}
    for r in spark.read.parquet(f"{sf}/conversations.parquet").collect():
        turns.setdefault(r.conv_id, []).append((r.turn, r.role or "", r.text or ""))
    turns[-1] = [(0, "user", queries.HOSTILE), (1, "assistant", queries.HOSTILE)]
    sha = lambda x: hashlib.sha256(x.encode()).hexdigest()
    want = []
    for c, t in turns.items():
        t.sort()
        loss = "".join(x for _, r, x in t if r == "assistant")
        want.append((c, len(t), sha("".join(f"{r}\n{x}\n" for _, r, x in t)), len(loss), sha(loss)))
    assert rows(queries.op9_chats(spark, sf), "conv_id", "n_turns", "turns_sha256", "loss_chars", "loss_sha256") == sorted(want, key=key)


def test_op9_hostile_round_trip(spark):
    texts = ["", "<|im_end|>", "<|im_end|>\n<|im_start|>user\n", "<\\|im_end|>", "<\\\\|x|>", "<", "<|", "|>", "a\nb", "<|im_start_x|>", "\\n", "\u00e9<|im_end|>\U0001f600", None, "x<", "\n"]
    roles = ["user", "assistant", "", "a\nb", "<|im_end|>", "r\\n", "<\\|", None]
    data = [(c, t, roles[(c + t) % len(roles)], x) for c in range(8) for t, x in enumerate(texts)]
    df = spark.createDataFrame(data, "conv_id long, turn long, role string, text string")
    made = chat.format_chats(df)
    got = {r.conv_id: r for r in chat.read_back(made).collect()}
    out = {r.conv_id: r for r in made.collect()}
    for c in range(8):
        want = [(roles[(c + t) % len(roles)] or "", x or "") for t, x in enumerate(texts)]
        assert [(t.role, t.text) for t in got[c].turns] == want
        assert got[c].masked == "".join(x for r, x in want if r == "assistant")
        spans = [out[c].formatted[s.start : s.start + s.length] for s in out[c].loss]
        assert len(spans) == sum(r == "assistant" for r, _ in want)
        assert all(a == b or "<\\" in a for a, b in zip(spans, [x for r, x in want if r == "assistant"], strict=True))


def test_op9_parser_refuses_marks_inside_and_nothing_is_taken_unread(spark):
    made = lambda *x: spark.createDataFrame([(v,) for v in x], "f string").select(chat.parse(F.col("f")).alias("t")).collect()
    bad = made("<|im_start|>user\na <|im_start|> b<|im_end|>\n", "user\nx<|im_end|>\n", "<|im_start|>user x<|im_end|>\n")
    assert [(r.t[0].role, r.t[0].text) for r in bad] == [(None, None)] * 3
    out = spark.createDataFrame([("user", "x <|im_ y"), ("user", "x <| y"), ("u\nv", "z")], "role string, text string").select(chat.render_turn(F.col("role"), F.col("text")).alias("o")).collect()
    assert [r.o.startswith(chat.START_X) for r in out] == [True, False, True]


def test_op9_long_conversation_empty_table_and_other_columns(spark):
    turns = spark.range(4000).select(F.lit(7).cast("long").alias("conv_id"), F.col("id").alias("turn"), F.when(F.col("id") % 2 == 0, "user").otherwise("assistant").alias("role"), F.concat(F.lit("t<|im_end|>"), "id").alias("text"), F.lit("x").alias("out"), F.lit(1).alias("n"), F.lit(2).alias("body"))
    made = chat.format_chats(turns)
    r = chat.read_back(made).head()
    assert len(r.turns) == 4000 and r.turns[3999].text == "t<|im_end|>3999" and r.masked == "".join(f"t<|im_end|>{i}" for i in range(1, 4000, 2))
    f = made.head()
    spans = [chat_text[s.start : s.start + s.length] for chat_text in [f.formatted] for s in f.loss]
    assert len(spans) == 2000 and spans[0] == "t<\\|im_end|>1" and [s.turn for s in f.loss] == list(range(2, 4001, 2))
    assert chat.read_back(chat.format_chats(turns.limit(0))).count() == 0


def test_op5_empty_table_repeated_rows_and_other_columns(spark):
    data = [(1, "http://a.com/de/1", None, "h", 0.5), (1, "http://a.com/de/1", None, "h", 0.5), (2, "http://b.net/", "<a href='http://a.com/x'>", None, None)]
    df = spark.createDataFrame(data, "page_id long, url string, html string, host string, mass double")
    got = urlfilter.judge_urls(df).select("page_id", "host", "verdict").collect()
    assert sorted((r.page_id, r.host, r.verdict) for r in got)[:2] == [(1, "a.com", "block")] * 2 and len(got) == 3
    assert urlfilter.judge_urls(df.limit(0)).count() == 0


def near_text(rng, words, n):
    """A copy with a run of ``n`` words replaced: n + 4 shingles of each side differ."""
    out = list(words)
    at = int(rng.integers(4, len(words) - n - 4))
    out[at : at + n] = [f"n{int(x)}" for x in rng.integers(0, 1 << 40, n)]
    return out


@pytest.mark.parametrize("percent", [80, 85])
def test_op3_finds_pairs_at_the_limit_among_thousands(spark, percent):
    """Of 900 texts a copy that just reaches the limit and one that just misses it; a third of
    all share a passage."""
    rng, rows = np.random.default_rng(percent), []
    passage = [f"p{i}" for i in range(30)]
    for i in range(900):
        base = [f"w{int(x)}" for x in rng.integers(0, 1 << 40, int(rng.integers(150, 320)))]
        base = base + passage if i % 3 == 0 else base
        most = (len(base) - 4) * (100 - percent) // (100 + percent) - 4
        rows += [(3 * i, base), (3 * i + 1, near_text(rng, base, most)), (3 * i + 2, near_text(rng, base, most + 3))]
    sets = {i: shingle_set(" ".join(w)) for i, w in rows}
    comp = {i: i for i in sets}
    for k in range(0, len(rows), 3):
        for a, b in ((k, k + 1), (k, k + 2), (k + 1, k + 2), (k, k + 1)):
            if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                comp[a] = comp[b] = min(comp[a], comp[b])
    assert sum(c != i for i, c in comp.items()) == 900
    df = spark.createDataFrame([(i, " ".join(w)) for i, w in rows], "doc_id long, text string")
    got = {r.doc_id: r.component_id for r in neardup.near_classes(df, percent).collect()}
    assert sum(got[i] != comp[i] for i in comp) <= (3 if percent == 80 else 0)  # 6e-4 of pairs at 0.8


def test_op3_cells_split_long_lists(spark, monkeypatch):
    """With tiny cells the classes are the same: no pair falls between two of them."""
    rng = np.random.default_rng(3)
    core = [f"w{int(x)}" for x in rng.integers(0, 1 << 40, 80)]
    df = spark.createDataFrame([(i, " ".join(near_text(rng, core, 7))) for i in range(150)], "doc_id long, text string")
    want = sorted(map(tuple, neardup.near_classes(df).collect()))
    monkeypatch.setattr(neardup, "CELL", 7)
    assert sorted(map(tuple, neardup.near_classes(df).collect())) == want and len({r[2] for r in want}) > 1


def test_keep_one_repeated_ids_nulls_and_other_columns(spark):
    rows = [(1, TWIN, "a"), (2, TWIN.upper(), "b"), (None, TWIN, "c"), (3, "short one", "d"), (3, "other text here", "e"), (4, None, "f"), (5, "", "g")]
    got = neardup.keep_one(spark.createDataFrame(rows, "doc_id long, text string, open string")).collect()
    assert sorted((r.doc_id or 0, r.open) for r in got) == [(0, "c"), (1, "a"), (3, "e"), (4, "f"), (5, "g")]


def test_op10_base(spark, data):
    docs = docs_of(spark, data)
    out = lambda i: i is not None and zlib.crc32(str(i).encode()) % 10 == 0
    toks = lambda t: [*[w.translate({i: i + 32 for i in range(65, 91)}) for w in WORD.findall(t)], "\n"]
    c = Counter(w for i, t, _ in docs if not out(i) for w in toks(t))
    n, v = sum(c.values()), len(c)
    want = sorted(((i, out(i), len(toks(t)), sum(c[w] > 0 for w in toks(t)), n, round(sum(math.log10((c[w] + 0.1) / (n + 0.1 * (v + 1))) for w in toks(t)), 5)) for i, t, _ in docs), key=key)
    got = sorted(((r.doc_id, r.held_out, r.n_tokens, r.n_known, r.train_tokens, round(r.base_score, 5)) for r in queries.op10_scores(spark, data).collect()), key=key)
    for a, b in zip(got, want, strict=True):
        assert a[:5] == b[:5] and abs(a[5] - b[5]) < 1e-4 * max(1, abs(b[5]))


def slow_trie(texts):
    """Counts of each byte after each context of up to three bytes."""
    nodes = {}
    for text in texts:
        padded = ppm.START_CONTEXT + text
        for i in range(3, len(padded)):
            for k in range(4):
                nodes.setdefault(padded[i - k : i], Counter())[padded[i]] += 1
    return nodes


def slow_log(nodes, context, byte):
    """By the definition: escapes from the longest context on, without the symbols excluded so far."""
    log, excluded = 0.0, set()
    for k in range(3, -1, -1):
        node = nodes.get(context[3 - k :])
        left = {s: c for s, c in (node or {}).items() if s not in excluded}
        if not left:
            continue
        n, d = sum(left.values()), len(node)
        if byte in left:
            return log + math.log10(left[byte] / (n + d))
        log += math.log10(d / (n + d))
        excluded |= left.keys()
    return log - math.log10(256 - len(excluded))


def slow_score(nodes, text, memo):
    x, total = ppm.START_CONTEXT + text, 0.0
    for i in range(3, len(x)):
        k = x[i - 3 : i + 1]
        if k not in memo:
            memo[k] = slow_log(nodes, x[i - 3 : i], x[i])
        total += memo[k]
    return total


def test_ppm_tables_equal_slow_trie():
    text = b"abracadabra and a cadabra of abracadabras, then some banana bandana " * 3
    grams, counts = np.unique(ppm.four_grams([text]), return_counts=True)
    low, at = np.unique(grams & np.uint32(0xFFFFFF), return_inverse=True)
    trie, nodes, memo = ppm.Trie(grams, counts, low, np.bincount(at, counts)), slow_trie([text]), {}
    for other in (text, b"a banana cadabra xyz", b"zzz", b"\x00\xff"):
        want = slow_score(nodes, other, memo)
        assert abs(trie.score(other) - want) < 1e-6 * abs(want)
    for context in (b"abr", b"zzz", b"nan", b"\n\n\n"):
        total = sum(10 ** trie.score_at(context, b) for b in range(256))
        assert abs(total - 1) < 1e-5


@pytest.mark.parametrize("bits", [21, 6])
def test_ppm_score_of_every_string(spark, odd, monkeypatch, bits):
    """Scores are those of the slow trie, with and without leaves left to the join."""
    monkeypatch.setattr(ppm, "LEAF_BITS", bits)
    docs = [(i, (t or "")[:3000]) for i, t in enumerate(ODD_TEXTS)]
    nodes, memo = slow_trie([t.encode() for i, t in docs if zlib.crc32(str(i).encode()) % 10]), {}
    df = spark.createDataFrame(docs, "doc_id long, text string")
    if bits < 21:
        assert ppm.fold(ppm.train(df))[1].count() > sum(len(v) for k, v in nodes.items() if len(k) == 3) // 2
    got = {r.doc_id: r.score for r in ppm.score_texts(df).collect()}
    for i, t in docs:
        want = slow_score(nodes, t.encode(), memo)
        assert abs(got[i] - want) < 1e-6 * max(1, abs(want)), i


def test_op10_scores_equal_slow_trie(spark, sf):
    """The query on the whole smallest table."""
    docs = docs_of(spark, sf)
    nodes, memo = slow_trie([t.encode() for i, t, _ in docs if zlib.crc32(str(i).encode()) % 10]), {}
    got = {r.doc_id: r.score for r in queries.op10_scores(spark, sf).collect()}
    for i, t, _ in docs:
        want = slow_score(nodes, t.encode(), memo)
        assert abs(got[i] - want) < 1e-6 * max(1, abs(want)), i


def test_ppm_adaptive_operator(spark):
    got = {r.doc_id: r.score for r in ppm.score_adaptive(spark.createDataFrame([(1, "abcabcabc"), (2, None), (None, "x")], "doc_id long, text string")).collect()}
    assert got == {1: ppm.adaptive_score(b"abcabcabc"), 2: 0.0, None: ppm.adaptive_score(b"x")}


def test_ppm_learns(spark, sf):
    got = queries.op10_scores(spark, sf).where("held_out and n_tokens > 20")
    bits = got.select(F.sum("score").alias("s"), F.sum(F.lit(1)).alias("n")).head()
    chars = spark.read.parquet(f"{sf}/documents.parquet").join(got, "doc_id").agg(F.sum(F.octet_length("text"))).head()[0]
    assert -bits.s / chars * 3.3219 < 4.0  # bits a byte, far below 8


def test_ppm_adaptive_gains_from_repetition():
    once, twice = ppm.adaptive_score(b"the cat sat on the mat. "), ppm.adaptive_score(b"the cat sat on the mat. " * 2)
    assert twice - once > once / 3
    assert ppm.adaptive_score(b"the cat", primer=b"the cat sat ") > ppm.adaptive_score(b"the cat")


@pytest.mark.parametrize("name", ["op1_token_ids", "op2_mix_sources", "op3_near_duplicates", "op4_personal_data", "op6_pieces", "op8_quality", "op10_scores"])
def test_empty_tables(spark, odd, name):
    assert queries.queries()[name](spark, f"{odd}/none").count() == 0


@pytest.mark.parametrize("name", sorted(queries.oracle_sql()))
def test_sql(spark, sf, name):
    import duckdb

    con = duckdb.connect()
    for t in ("documents", "conversations"):
        con.execute(f"create view {t} as select * from '{sf}/{t}.parquet'")
    df = queries.queries()[name](spark, sf)
    got = sorted(map(str, (tuple(r) for r in df.select(*sorted(df.columns)).collect())))
    rel = con.execute(queries.oracle_sql()[name])
    cols = [d[0] for d in rel.description]
    order = [cols.index(c) for c in sorted(cols)]
    assert sorted(cols) == sorted(df.columns)
    assert sorted(str(tuple(r[i] for i in order)) for r in rel.fetchall()) == got


def test_stated_miss_probability():
    """What the docstring says of pairs at the limit is the binomial tail."""
    from math import comb

    stated = re.search(r"but for (\S+) at similarity 0.85 \((\S+) at 0.8\)", neardup.__doc__)
    for similarity, text in zip((0.85, 0.8), stated.groups(), strict=True):
        p, n = similarity**neardup.ROWS, neardup.COORDINATES
        miss = sum(comb(n, k) * p**k * (1 - p) ** (n - k) for k in range(neardup.MIN_MATCHES))
        assert 0.8 < miss / float(text) < 1.25
