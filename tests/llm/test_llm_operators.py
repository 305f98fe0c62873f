"""Each operator against brute force, with nulls, empty and long texts, ties, repeated rows, empty tables and clashing columns."""

import hashlib
import math
import random
import re
from collections import Counter

import numpy as np
import pytest
from hypothesis import given, settings
from hypothesis import strategies as st

import public_tokenizers
from raydescent.llm.common import table

DOCS = "doc_id long, text string, lang string, source string, n_chars long"
BYTE, WORD = public_tokenizers.path("byte_bpe_50k.json"), public_tokenizers.path("word_bpe_49k.json")


@pytest.fixture(scope="module")
def odd(spark):
    """Awkward rows: null, empty and letterless texts, copies, a repeated row, a null id, a very long text."""
    rng = random.Random(3)
    long = " ".join(rng.choice(["the", "House", "und", "le", "grün", "x1"]) for _ in range(60_000))
    texts = [None, "", "   ", "12 34 !?", "The cat sat on the mat.", "The  cat\tsat on\nthe mat.", "the cat sat on the mat.", long, long + " end", "<|endoftext|> a<|endoftext|>", "日本語 😀 text", "Under the MIT License. Under the MIT license", "kİ K", "a", "a", "The cat sat on the mat."]
    rows = [(i, t, "en", "s", len(t or "")) for i, t in enumerate(texts)] + [(4, texts[4], "en", "s", 23), (None, "Nobody owns this text", None, None, None)]
    return spark.createDataFrame(rows, DOCS).repartition(3)


@pytest.fixture(scope="module")
def empty(spark):
    return spark.createDataFrame([], DOCS)


def texts_of(df):
    return [(r.doc_id, r.text) for r in df.collect()]


# Exact dedup


def test_trie_against_a_dictionary_with_spill():
    from raydescent.llm.patricia_dedup import PatriciaTrie

    rng = random.Random(1)
    keys = [bytes(rng.choices(b"ab", k=rng.randint(0, 12))) + b"x" * rng.randint(0, 3) for _ in range(4000)]
    for budget in (1 << 30, 20_000, 3_000):
        trie, want = PatriciaTrie(budget), {}
        for i, k in enumerate(keys):
            owner = rng.randint(0, 10**6)
            trie.insert(k, owner)
            want[k] = (min(owner, want[k][0]) if k in want else owner, want.get(k, (0, 0))[1] + 1)
            del i
        got = list(trie.items())
        assert len(got) == len(want) and {k: (o, n) for k, o, n, _ in got} == want


@settings(max_examples=50, deadline=None)
@given(st.lists(st.binary(max_size=6), max_size=40))
def test_trie_keeps_every_string(keys):
    from raydescent.llm.patricia_dedup import PatriciaTrie

    trie = PatriciaTrie(900)
    for i, k in enumerate(keys):
        trie.insert(k, i)
    assert sorted((k, n) for k, _, n, _ in trie.items()) == sorted(Counter(keys).items())


def test_trie_spills_leaves_and_keeps_one_long_string():
    from raydescent.llm.patricia_dedup import PatriciaTrie

    rng = random.Random(2)
    keys = [bytes([c]) * 500 + bytes(rng.choices(b"xy", k=5)) for c in range(40)] + [b"p" * 5000, b"p" * 5000 + b"q" * 9000, b"p" * 4999]
    trie = PatriciaTrie(2_000)
    for i, k in enumerate(keys * 3):
        trie.insert(k, i)
        assert trie.held < 2_000 + 9_500 + 43 * 700  # what one string and the first bytes of the others take
    assert sorted((k, o, n) for k, o, n, _ in trie.items()) == sorted((k, i, 3) for i, k in enumerate(keys))
    alone = PatriciaTrie(10)
    alone.insert(b"z" * 1000, 1)
    alone.insert(b"z" * 1000, 0)
    assert list(alone.items()) == [(b"z" * 1000, 0, 2, 1)]


def test_exact_dedup_keeps_columns_of_its_own_names(spark, odd):
    from raydescent.llm.patricia_dedup import exact_dedup

    names = {"lang": "kept", "source": "group_size", "n_chars": "text_sha256"}
    docs = odd.selectExpr("*", "'k' AS keep_id", "'t' AS _ties", "map('a', 1) AS m", "'dot' AS `a.b`", "1 AS _f", "2 AS _jk").withColumnsRenamed(names)
    got = exact_dedup(docs)
    assert got.schema == docs.schema
    assert got.where("kept = 'en' AND keep_id = 'k' AND _ties = 't' AND m['a'] = 1 AND _f = 1 AND _jk = 2").count() == got.count() - 1 > 5


def test_exact_dedup(spark, odd, empty):
    from raydescent.llm.patricia_dedup import assign_owners, exact_dedup

    norm = lambda t: re.sub("[\x20\x09-\x0d]+", " ", t or "")
    rows = texts_of(odd)
    groups = {}
    for i, t in rows:
        groups.setdefault(norm(t), []).append(i)
    got = assign_owners(odd.withColumnRenamed("source", "kept")).collect()
    assert len(got) == len(rows)
    for r in got:
        ids = groups[norm(r.text)]
        least = min((i for i in ids if i is not None), default=None)
        assert (r.keep_id, r.group_size) == (least, len(ids)) and r.text_sha256 == hashlib.sha256(norm(r.text).encode()).hexdigest()
    assert sum(r.kept for r in got) == len(groups) + 1  # one text has a row that repeats its smallest id
    kept = exact_dedup(odd)
    assert kept.columns == odd.columns and kept.count() == len(groups)
    assert exact_dedup(empty).count() == 0


# Host reputation


def test_urls(spark):
    from raydescent.llm.url_reputation import UrlRule, filter_urls, judge_urls

    urls = [(0, "http://A.Example.ORG/es/1?q"), (1, "https://example.org/en/12"), (2, "http://x.com/fr/"), (3, "http://x.com/de/#a"), (4, "no scheme"), (5, None), (6, "http://bad.example.net:80/p"), (7, "http://org"), (8, "http://notexample.org/es/"), (9, "http://1.2.3.4/x"), (10, "://h?x=/y"), (11, "http://a/b://c/d"), (12, "")]
    urls += [(100 + i, f"http://spam.example.net/{i}") for i in range(60)] + [(200 + i, f"http://good.example.net/{i}") for i in range(60)]
    pages = spark.createDataFrame([(i, u, "v") for i, u in urls], "page_id long, url string, verdict string")
    labels = spark.createDataFrame([(100 + i, 0) for i in range(40)] + [(200 + i, 1) for i in range(40)] + [(6, None)], "page_id long, good int")
    got = {r.page_id: r for r in judge_urls(pages, labels).collect()}
    assert len(got) == len(urls)
    assert [(got[i].host, got[i].path, got[i].rule, got[i].verdict) for i in (0, 1, 2, 3, 8)] == [
        ("a.example.org", "/es/1", "example.org/es/", "block"), ("example.org", "/en/12", "example.org/en/1", "block"), ("x.com", "/fr/", "com/fr/", "allow"), ("x.com", "/de/", "com/de/", "block"), ("notexample.org", "/es/", "org/", "allow")]
    assert [(got[i].host, got[i].path) for i in (4, 5, 10, 11, 12)] == [("", ""), ("", ""), ("h", ""), ("a", "/b://c/d"), ("", "")]
    assert got[7].path == "" and got[7].rule is None
    assert all(got[100 + i].verdict == "block" for i in range(60)) and all(got[200 + i].verdict == "allow" for i in range(60))
    assert got[6].verdict == "allow"  # one host without labels is not condemned for its neighbours
    kept = filter_urls(pages, labels)
    assert kept.columns == pages.columns and kept.count() == sum(r.verdict == "allow" for r in got.values())
    nothing = judge_urls(pages.limit(0), labels.limit(0))
    assert nothing.count() == 0
    assert judge_urls(pages, labels.limit(0), rules=(UrlRule.parse("block x.com/"),)).where("verdict = 'block'").count() == 2


def test_domains_of_odd_hosts(spark):
    from pyspark.sql import functions as F

    from raydescent.llm.url_reputation import domain_parts, judge_urls

    hosts = {"bad.example.net:80": ("example.net", "net"), "u@x.com": ("x.com", "com"), "u:p@a.b.co.uk:8080": ("b.co.uk", "co.uk"), "a.example.com.": ("example.com", "com"), "1.2.3.4:80": ("1.2.3.4", ""), "[::1]:80": ("[::1]", ""), "[2001:db8::2]": ("[2001:db8::2]", ""), "localhost": ("localhost", "localhost"), "": ("", "")}
    rows = spark.createDataFrame([(h,) for h in hosts], "host string")
    domain, suffix = domain_parts(F.col("host"))
    assert {r.host: (r.d, r.s) for r in rows.select("host", domain.alias("d"), suffix.alias("s")).collect()} == hosts
    own, _ = domain_parts(F.col("host"), ("example.net",))
    assert rows.where("host LIKE 'bad%'").select(own.alias("d")).first().d == "bad.example.net"
    pages = spark.createDataFrame([(i, f"http://h{i % 9}.spam.net:{80 + i % 3}/") for i in range(300)] + [(900, "http://new.spam.net:99/"), (901, "http://q.fine.org:99/")], "page_id long, url string")
    labels = spark.createDataFrame([(i, 0) for i in range(300)], "page_id long, good int")
    got = {r.page_id: r for r in judge_urls(pages, labels).collect()}
    assert got[900].verdict == "block" and got[900].host == "new.spam.net:99"  # its domain's ports are one domain
    assert all(0 <= r.good_upper <= 1 for r in got.values())


def test_url_filter_keeps_columns_of_its_own_names(spark):
    from raydescent.llm.url_reputation import filter_urls

    pages = spark.createDataFrame([(1, "http://a.org/x", "h", "p", "n", "u", "f")], "page_id long, url string, _host string, _path string, _pages string, _upper string, _f string")
    assert filter_urls(pages, spark.createDataFrame([], "page_id long, good int")).collect() == pages.collect()


# Vectors


def test_links_are_counted_by_cells(spark, monkeypatch):
    """A chain of crowds in one component: cells far apart are not multiplied, and no link is lost."""
    from pyspark.sql import functions as F

    from raydescent.llm import nn_descent as m

    rng = np.random.default_rng(6)
    turn = np.linspace(0, 5.5, 600)
    x = np.column_stack([np.cos(turn), np.sin(turn), *(rng.standard_normal((6, 600)) * 0.03)])
    x = np.vstack([x, np.repeat(x[:1], 80, axis=0) + rng.standard_normal((80, 8)) * 0.02, rng.standard_normal((30, 8))])
    u = x / np.linalg.norm(x, axis=1, keepdims=True)
    rows = [(i, 7 if i < 680 else 1000 + i // 2, 1 + i % 3, bytearray(v.astype("<f8").tobytes())) for i, v in enumerate(x)]
    members = spark.createDataFrame(rows, "node long, component long, members long, raw binary").select("component", "node", "members", "raw").repartition(4).persist()
    comp, many = np.array([r[1] for r in rows]), np.array([r[2] for r in rows])
    met = (u @ u.T >= 0.9) & (comp[:, None] == comp[None, :]) & ~np.eye(len(rows), dtype=bool)
    for part, pivots in ((16, 8192), (16, 3), (16, 0), (4000, 8192)):
        monkeypatch.setattr(m, "LEAST_PART", part)
        monkeypatch.setattr(m, "PIVOTS", pivots)
        seen = []
        near = m._near_cells
        monkeypatch.setattr(m, "_near_cells", lambda *a: seen.append(near(*a)) or seen[-1])
        got = {r.node: r.linked for r in m.count_links(members, "<f8", 0.9).collect()}
        monkeypatch.setattr(m, "_near_cells", near)
        assert [got.get(i, 0) for i in range(len(rows))] == (met @ many).tolist()
        if (part, pivots) == (16, 8192):
            cells = len({r[1] for r in seen[0]})
            assert cells > 20 and len(seen[0]) < 0.6 * cells * cells
    members.unpersist()


def test_tables_grow_with_the_rows(spark):
    """Isolated pairs at the threshold, searched with the directions that a million rows would have."""
    from raydescent.llm.nn_descent import audited_components, block_bits, block_tables

    rng = np.random.default_rng(8)
    base = rng.standard_normal((1500, 64))
    base /= np.linalg.norm(base, axis=1, keepdims=True)
    side = rng.standard_normal((300, 64))
    side -= (side * base[:300]).sum(axis=1, keepdims=True) * base[:300]
    side /= np.linalg.norm(side, axis=1, keepdims=True)
    x = np.vstack([base, 0.905 * base[:300] + math.sqrt(1 - 0.905**2) * side])
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(x)], "vec_id long, embedding array<double>").repartition(4)
    bits = block_bits(1_000_000)
    assert bits == 11 and block_tables(bits, 0.9) < block_tables(block_bits(10**9), 0.9) < 150
    result, recall = audited_components(df, bits=bits, tables=block_tables(bits, 0.9), rounds=1)
    assert recall >= 0.9 and result.where("n_links > 0").count() >= 2 * 300 * 0.95
    few, low = audited_components(df, bits=bits, tables=1, rounds=0, attempts=2, least_recall=0.99)
    assert low < 0.99 and few.where("n_links > 0").count() < 600


def test_vectors_against_brute_force(spark):
    from raydescent.llm.nn_descent import audit_recall, vector_components

    rng = np.random.default_rng(2)
    centres = rng.standard_normal((900, 24))
    x = [c for c in centres]
    for i in range(200):
        x += [centres[i] + rng.standard_normal(24) * 0.15 for _ in range(rng.integers(1, 4))]
    x += [centres[0] + rng.standard_normal(24) * 0.1 for _ in range(300)]  # a crowd
    x += [centres[5], centres[5] * 2.0, centres[5]]
    rows = [(i, v.tolist()) for i, v in enumerate(x)]
    n = len(rows)
    rows += [(n, None), (n + 1, [0.0] * 24), (n + 2, [math.nan] * 24), (n + 3, [None] * 24), (n + 4, []), (n + 5, [1.0]), (n + 6, [2.0]), (None, centres[7].tolist())]
    df = spark.createDataFrame([(i, v, "k") for i, v in rows], "vec_id long, embedding array<double>, kept string").repartition(4)
    got = {r.vec_id: r for r in vector_components(df).collect()}
    assert len(got) == len(rows)
    u = np.array(x) / np.linalg.norm(x, axis=1, keepdims=True)
    near = u @ u.T >= 0.9
    degree = near.sum(axis=1) - 1
    degree += (u @ (centres[7] / np.linalg.norm(centres[7])) >= 0.9).astype(int)
    found = np.array([got[i].n_links for i in range(n)])
    assert (found == degree).mean() >= 0.99 and (found <= degree).all()
    for i in range(n + 5):
        if i >= n:
            assert got[i].n_links == 0 and got[i].component_id == i and got[i].kept
    assert got[n + 5].n_links == 1 and got[n + 6].component_id == n + 5
    assert got[None].component_id == 7
    audit = audit_recall(df, vector_components(df)).first()
    assert audit.recall >= 0.95 and audit.queries == sum(1 for i in range(0, n + 7, 20) if i < n or i in (n + 5, n + 6))
    assert vector_components(df.limit(0)).count() == 0


def test_equal_vectors_under_one_id(spark):
    from raydescent.llm.nn_descent import vector_components

    df = spark.createDataFrame([(1, [1.0, 0.0]), (1, [0.0, 1.0]), (1, [1.0, 0.0]), (2, [0.0, 2.0])], "vec_id long, embedding array<float>")
    got = sorted((r.vec_id, r.n_links, r.component_id) for r in vector_components(df).collect())
    assert got == [(1, 1, 1), (1, 1, 1), (1, 1, 1), (2, 1, 1)]


def test_links_of_two_crowds_met_in_a_join(spark):
    """Both lists are full of closer ones; the pair is a link all the same, and the only one between the crowds."""
    from raydescent.llm.nn_descent import improve

    at = {0: (1.0, 0.0), 1: (math.cos(0.35), math.sin(0.35)), 9: (math.cos(0.6), -math.sin(0.6))}
    nodes = spark.createDataFrame([(i, bytearray(np.array(v, "<f8").tobytes())) for i, v in at.items()], "node long, raw binary")
    lists = spark.createDataFrame([(9, 0, 0.5, False, 10), (9, 1, 0.5, False, 10)], "node long, near long, cos double, old boolean, k int")
    state = spark.createDataFrame([(0, 10, 0.99), (1, 10, 0.99), (9, 10, -2.0)], "node long, k int, tau double")
    got = {(min(r.node, r.near), max(r.node, r.near)) for r in improve(lists, state, nodes, 10, "<f8").collect()}
    assert (0, 1) in got


# Tokens


@pytest.fixture(scope="module")
def library():
    from tokenizers import Tokenizer

    return Tokenizer.from_file(BYTE)


@settings(max_examples=300, deadline=None)
@given(st.text(max_size=60) | st.text(alphabet="aeiou thsn'reENT12.\n  ", max_size=80))
def test_automaton_equals_the_library(library, text):
    from raydescent.llm.bpe_automaton import compiled, read_vocabulary

    bpe = compiled(read_vocabulary(BYTE))
    ids = bpe.encode(text)
    assert np.frombuffer(ids, "<u4").tolist() == library.encode(text, add_special_tokens=False).ids
    assert bpe.decode(ids) == text


def test_automaton_on_every_latin_character(library):
    from raydescent.llm.bpe_automaton import LATIN_END, compiled, read_vocabulary

    bpe = compiled(read_vocabulary(BYTE))
    for c in range(LATIN_END + 40):
        for text in (f"a{chr(c)}b {chr(c)} {chr(c)}{chr(c)}1{chr(c)}!", chr(c) * 40):
            assert np.frombuffer(bpe.encode(text), "<u4").tolist() == library.encode(text, add_special_tokens=False).ids, hex(c)


def test_gadgets_of_a_small_vocabulary():
    from raydescent.llm.bpe_automaton import TokenAutomaton

    spelling, merges = [b"a", b"b", b"aa", b"ab", b"aab"], [(0, 0, 2), (0, 1, 3), (2, 1, 4)]
    auto = TokenAutomaton(spelling, [0, 1], merges)
    for n in range(1, 9):
        for bits in range(1 << n):
            word = bytes(b"ab"[bits >> i & 1] for i in range(n))
            tokens = [[0, 1][c == ord("b")] for c in word]
            for u, v, w in merges:  # the definition: each merge from left to right, in order
                out, i = [], 0
                while i < len(tokens):
                    if tokens[i : i + 2] == [u, v]:
                        out.append(w)
                        i += 2
                    else:
                        out.append(tokens[i])
                        i += 1
                tokens = out
            assert auto.encode_word(word) == tokens


def test_encode_query(spark, odd, empty, library):
    from raydescent.llm.bpe_automaton import decode_texts, encode_digests, encode_texts

    rows = sorted((r.doc_id is None, r.doc_id or 0, r.n_tokens, r.ids_sha256, r.decoded_sha256) for r in encode_digests(odd, BYTE).collect())
    want = []
    for i, t in texts_of(odd):
        ids = library.encode(t or "", add_special_tokens=False).ids
        want.append((i is None, i or 0, len(ids), hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest(), hashlib.sha256((t or "").encode()).hexdigest()))
    assert rows == sorted(want)
    assert encode_digests(empty, BYTE).count() == 0
    back = decode_texts(encode_texts(odd.withColumnRenamed("lang", "token_ids"), BYTE).drop("text"), BYTE)
    assert sorted(r.text for r in back.collect()) == sorted(t or "" for _, t in texts_of(odd))


def test_each_byte_is_one_look_up(library):
    """A word costs as many look-ups as it has bytes, and arcs beyond the compiled ones are found again or made anew."""
    import pickle

    from raydescent.llm.bpe_automaton import ByteBpe, compiled, read_vocabulary

    bpe = pickle.loads(pickle.dumps(compiled(read_vocabulary(BYTE))))
    auto, asked = bpe.automaton, []

    class Counted(dict):
        def get(self, key):
            asked.append(key)
            return dict.get(self, key)

    auto.most_extra, resets = 300, []
    reset = auto._reset
    auto._reset = lambda: (resets.append(1), reset())
    assert isinstance(bpe, ByteBpe) and auto.compiled_states >= 90_000
    rng = random.Random(9)
    for n in range(200):
        word = "".join(rng.choices("abcdefghijklmnopqrstuvwxyzé", k=rng.randint(1, 40)))
        auto.table = Counted(auto.table) if n % 20 == 0 or not isinstance(auto.table, Counted) else auto.table
        asked.clear()
        got = auto.encode_word(word.encode())
        assert len(asked) <= len(word.encode()) and (resets or len(asked) == len(word.encode()))
        assert got == library.encode(word, add_special_tokens=False).ids
    assert resets and len(auto.states) <= auto.compiled_states + 302


def test_separator_scan(spark, odd, empty, library, tmp_path, monkeypatch):
    from raydescent.llm import separator_scan as m

    library.encode_special_tokens = True
    want = sorted((i is None, i or 0, len(library.encode(t or "", add_special_tokens=False).ids)) for i, t in texts_of(odd))
    library.encode_special_tokens = False
    written = m.write_flat(odd.withColumnRenamed("source", "stream"), BYTE, 50_256, f"file://{tmp_path}/flat")
    for size in (64, 1 << 16):
        counted = m.count_tokens(m.flat_files(spark, f"file://{tmp_path}/flat/*.bin", block_tokens=size), 50_256)
        got = counted.selectExpr("substring_index(stream, '/', -1) stream", "number", "n_tokens", "ended").join(written, ["stream", "number"]).collect()
        assert all(r.ended for r in got)
        assert sorted((r.id is None, r.id or 0, r.n_tokens) for r in got) == want
    squeezed = m.write_flat(odd, BYTE, 50_256, f"file://{tmp_path}/zst", compress=True)
    counted = m.count_tokens(m.flat_files(spark, f"file://{tmp_path}/zst/*", block_tokens=100), 50_256)
    got = counted.selectExpr("substring_index(stream, '/', -1) stream", "number", "n_tokens").join(squeezed, ["stream", "number"]).collect()
    assert sorted((r.id is None, r.id or 0, r.n_tokens) for r in got) == want
    assert m.write_flat(empty, BYTE, 50_256, f"file://{tmp_path}/none").count() == 0
    rng = np.random.default_rng(0)
    for name, n in (("a", 1000), ("b", 0), ("c", 5)):
        rng.integers(0, 9, n).astype("<u2").tofile(tmp_path / f"{name}.bin")
    for span in (1 << 24, 64):  # the whole file, or ranges of two blocks
        monkeypatch.setattr(m, "RANGE_BYTES", span)
        blocks = m.flat_files(spark, f"file://{tmp_path}/*.bin", block_tokens=16)
        got = m.count_tokens(blocks, 8).collect()
        assert blocks.count() == 63 + 1
        for name in "abc":
            ids = np.fromfile(tmp_path / f"{name}.bin", "<u2").tolist()
            cuts, want, start = [i for i, x in enumerate(ids) if x == 8], [], 0
            for number, c in enumerate([*cuts, len(ids)]):
                if c < len(ids) or start < c:
                    want.append((number, start, c - start, c < len(ids)))
                start = c + 1
            assert sorted((r.number, r.start, r.n_tokens, r.ended) for r in got if r.stream.endswith(f"{name}.bin")) == want
    (tmp_path / "odd.bin").write_bytes(b"abc")
    with pytest.raises(Exception, match="whole ids"):
        m.flat_files(spark, f"file://{tmp_path}/odd.bin").count()


# Licences


def test_licences(spark, odd, empty):
    from raydescent.llm.license_votes import TEMPLATES, license_spans, scan_licenses

    word = re.compile(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+")
    lower = str.maketrans("ABCDEFGHIJKLMNOPQRSTUVWXYZ", "abcdefghijklmnopqrstuvwxyz")
    got = {r.doc_id: r for r in scan_licenses(odd.withColumnRenamed("lang", "label")).collect()}
    for i, t in texts_of(odd):
        assert got[i].n_words == len(word.findall((t or "").translate(lower)))
    assert (got[11].n_base, got[11].first_word, got[11].last_word, got[11].base_labels) == (2, 0, 4, "mit")
    assert got[4].labels == "" and got[4].score == 0.0
    assert scan_licenses(empty).count() == 0
    full = TEMPLATES[0][1]
    altered = full.replace("free of charge ", "wholly free of charge ").replace("software without", "thing without")
    texts = [f"intro words {altered} and more", full + " " + full, "cc by nc by cc by nc", " ".join(full.split()[::-1]), full[:60]]
    more = scan_licenses(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"))
    got = {r.doc_id: r for r in more.collect()}
    assert got[0].labels == "mit" and got[0].n_base == 0 and 0.6 <= got[0].score < 1 and got[1].score == 1.0
    assert got[2].n_base == 2 and got[2].labels == "cc-by-nc" and got[3].labels == "" and got[4].labels == ""
    spans = license_spans(spark.createDataFrame([(0, texts[0])], "doc_id long, text string")).where("label IS NOT NULL").collect()
    assert [(s.first_word, s.end_word) for s in spans] == [(2, 2 + altered.split().index("thing"))]


# SimHash


def test_simhash(spark, odd, empty):
    import xxhash

    from raydescent.llm.bit_planes import join_labels
    from raydescent.llm.simhash_dedup import near_dedup, simhash_components

    def print_of(t):
        w = re.findall("[^\x20\x09-\x0d]+", "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in t or ""))
        s = [" ".join(w[i : i + 3]) for i in range(len(w) - 2)] if len(w) >= 3 else [" ".join(w)] if w else []
        hs = [xxhash.xxh64_intdigest(x.encode(), 42) for x in s]
        return sum((2 * sum(h >> b & 1 for h in hs) > len(hs)) << b for b in range(64))

    rows = [(i, t) for i, t in texts_of(odd) if t is None or len(t) < 1000]
    got = simhash_components(odd.where("n_chars < 1000 OR n_chars IS NULL")).collect()
    prints = {t: print_of(t) for _, t in rows}
    assert sorted((r.doc_id or -1, r.fingerprint) for r in got) == sorted((i or -1, f"{prints[t]:016x}") for i, t in rows)
    label = list(range(len(rows)))
    pairs = [(a, b) for a in range(len(rows)) for b in range(a) if (prints[rows[a][1]] ^ prints[rows[b][1]]).bit_count() <= 3]
    label = join_labels(np.array(label), np.array([p[0] for p in pairs]), np.array([p[1] for p in pairs]))
    least = {c: min((rows[j][0] for j in range(len(rows)) if label[j] == c and rows[j][0] is not None), default=None) for c in set(label.tolist())}
    want = sorted((rows[j][0] is None, rows[j][0] or 0, least[int(label[j])] is None, least[int(label[j])] or 0) for j in range(len(rows)))
    assert sorted((r.doc_id is None, r.doc_id or 0, r.component_id is None, r.component_id or 0) for r in got) == want
    assert simhash_components(empty).count() == 0 and near_dedup(empty).count() == 0
    kept = near_dedup(odd)
    assert kept.columns == odd.columns
    nobody = spark.createDataFrame([(None, "one two three four"), (None, "quite another set of words"), (8, "one two three four")], "doc_id long, text string")
    assert sorted((r.doc_id or 0, r.component_id or 0) for r in simhash_components(nobody).collect()) == [(0, 0), (0, 8), (8, 8)]


def test_bit_planes_against_brute_force():
    from raydescent.llm.bit_planes import close_pairs

    rng = np.random.default_rng(0)
    for width, radius in ((8, 0), (8, 3), (24, 30)):
        x = rng.integers(0, 256, (900, width), dtype=np.uint8)
        for i in range(300):
            x[i + 300] = x[i]
            for _ in range(rng.integers(0, 2 * radius + 2)):
                b = rng.integers(0, width * 8)
                x[i + 300, b // 8] ^= np.uint8(1 << b % 8)
        order = rng.permutation(900)
        x, group = x[order], np.sort(rng.integers(0, 3, 900))
        got = {(int(a), int(b)) for i, j in close_pairs(x, group, radius) for a, b in zip(i, j)}
        want = {(i, j) for i in range(900) for j in range(i + 1, 900) if group[i] == group[j] and np.bitwise_count(x[i] ^ x[j]).sum() <= radius}
        assert got == want


def test_near_copies_of_given_similarity(spark):
    from raydescent.llm.simhash_dedup import near_dedup, shingle_hashes

    rng = random.Random(5)
    words = [f"w{i}" for i in range(3000)]
    base = [[rng.choice(words) for _ in range(200)] for _ in range(120)]
    texts = [" ".join(b) for b in base]
    for b in base[:60]:  # a word changed in the middle costs five shingles of 196
        c = list(b)
        for _ in range(rng.randint(1, 4)):
            c[rng.randrange(200)] = "new"
        texts.append(" ".join(c))
    shared = base[0][:100]
    texts += [" ".join(shared + [rng.choice(words) for _ in range(100)]) for _ in range(10)]  # similar in half: all stay
    sets = [set(shingle_hashes(t, 5).tolist()) for t in texts]
    linked = {j for j in range(120, 180) if len(sets[j] & sets[j - 120]) / len(sets[j] | sets[j - 120]) >= 0.8}
    got = {r.doc_id for r in near_dedup(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string"), cosine=False).collect()}
    assert len(linked) > 50 and len(got & linked) <= 1
    assert set(range(len(texts))) - linked <= got


def near_copies(texts, least=0.8, cosine=False):
    """Rows that are linked, directly or through others, to a row before them; by brute force."""
    from raydescent.llm.bit_planes import join_labels
    from raydescent.llm.simhash_dedup import shingle_hashes

    sets = [set(shingle_hashes(t, 5).tolist()) for t in texts]
    alike = lambda a, b, both: both >= least * math.sqrt(max(1, len(a) * len(b))) if cosine else both >= least * max(1, len(a) + len(b) - both)
    pairs = [(i, j) for i in range(len(sets)) for j in range(i) if sets[i] and sets[j] and alike(sets[i], sets[j], len(sets[i] & sets[j]))]
    label = join_labels(np.arange(len(sets)), np.array([p[0] for p in pairs], int), np.array([p[1] for p in pairs], int))
    return {i for i in range(len(sets)) if label[i] < i}


def test_near_copies_under_one_fingerprint(spark):
    """One shingle makes over half of each text, so that it alone decides a fingerprint that counts repeats."""
    from raydescent.llm.simhash_dedup import near_dedup

    rng = random.Random(11)
    some = lambda n: " ".join(f"w{rng.randrange(10**6)}" for _ in range(n))
    filler = "- " * 400
    texts = [filler + some(60), *(filler + some(120) for _ in range(4))]
    texts += [t + " end" for t in texts[1:]]
    assert near_copies(texts) == {5, 6, 7, 8}
    got = {r.doc_id for r in near_dedup(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got == {0, 1, 2, 3, 4}


def test_near_copies_with_repeated_passages(spark):
    from raydescent.llm.simhash_dedup import near_dedup

    rng = random.Random(12)
    texts = []
    for _ in range(8):
        p, q = (" ".join(f"w{rng.randrange(10**6)}" for _ in range(300)) for _ in range(2))
        texts += [f"{p} {q}", f"{p} " * 20 + q]
    assert near_copies(texts) == set(range(1, 16, 2))
    got = {r.doc_id for r in near_dedup(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert got == set(range(0, 16, 2))


def test_near_copies_in_a_dense_family(spark, monkeypatch):
    """Pages of one template: nearly all pairs lie just below 0.8, so that near fingerprints do not tell the copies."""
    from raydescent.llm import simhash_dedup as m

    rng = random.Random(13)
    page = [f"w{i}" for i in range(400)]

    def changed(words, times):
        out = list(words)
        for p in rng.sample(range(0, len(out), 5), times):
            out[p] = f"n{rng.randrange(10**9)}"
        return out

    texts = [changed(page, 6) for _ in range(500)]
    texts += [changed(texts[i], 16) for i in range(0, 500, 4)]
    texts = [" ".join(t) for t in texts]
    want = near_copies(texts, 0.81)
    docs = spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(4)
    for rows in (20_000, 150):
        monkeypatch.setattr(m, "FAMILY_ROWS", rows, raising=False)
        got = {r.doc_id for r in m.near_dedup(docs, least=0.81, cosine=False).collect()}
        assert set(range(len(texts))) - got == want


def test_family_links_against_brute_force(monkeypatch):
    from raydescent.llm import simhash_dedup as m
    from raydescent.llm.bit_planes import join_labels

    monkeypatch.setattr(m, "_BLOCK", 16)
    monkeypatch.setattr(m, "_COLUMNS", 64)
    rng = np.random.default_rng(4)
    for n, sides in ((2, False), (130, False), (130, True), (1, False)):
        base = rng.choice(10**6, 90, replace=False)
        sets = [np.unique(np.r_[base[rng.random(90) < 0.9], rng.choice(10**6, rng.integers(0, 12))]).astype(np.uint64) for _ in range(n)]
        side = rng.integers(0, 2, n) if sides else None
        share = np.array([[len(np.intersect1d(x, y)) / len(np.union1d(x, y)) for y in sets] for x in sets])
        angle = np.array([[len(np.intersect1d(x, y)) / math.sqrt(len(x) * len(y)) for y in sets] for x in sets])
        for cosine, share in ((True, angle), (False, share)):
            i, j, s = m._family_links(sets, side, 0.8, cosine)
            assert np.allclose(s, share[i, j]) and (s >= 0.8).all()
        met = (share >= 0.8) & (True if side is None else side[:, None] != side[None, :])
        assert n < 100 or 0 < met.mean() < 0.9
        assert np.array_equal(join_labels(np.arange(n), i, j), join_labels(np.arange(n), *np.nonzero(met)))


def test_large_buckets_are_dealt_in_parts(spark, monkeypatch):
    from raydescent.llm import simhash_dedup as m

    monkeypatch.setattr(m, "BUCKET_ROWS", 20)
    rng = np.random.default_rng(1)
    base = rng.integers(0, 256, 8, dtype=np.uint8)
    rows = []
    for i in range(150):
        x = base.copy()
        for b in rng.integers(0, 24, 4):
            x[b // 8] ^= np.uint8(1 << int(b) % 8)
        rows.append((i, bytearray(x.tobytes())))
    nodes = spark.createDataFrame(rows, "node long, print binary").dropDuplicates(["print"])
    links = m.close_links(nodes, m.exact_tables(64, 3, 5), 3)
    from raydescent.llm.components import connected_components

    got = {r.node: r.component for r in connected_components(links).collect()}
    held = nodes.collect()
    v = {r.node: np.frombuffer(bytes(r.print), np.uint8) for r in held}
    label = {n: n for n in v}
    changed = True
    while changed:
        changed = False
        for a in v:
            for b in v:
                if np.bitwise_count(v[a] ^ v[b]).sum() <= 3 and label[a] > label[b]:
                    label[a], changed = label[b], True
    assert {n: got.get(n, n) for n in v} == label


def test_components_of_a_path_and_a_star(spark):
    from raydescent.llm.components import connected_components

    links = [(i, i + 1) for i in range(100, 160)] + [(500, i) for i in range(501, 560)] + [(7, 7)]
    got = {r.node: r.component for r in connected_components(spark.createDataFrame(links, "a long, b long")).collect()}
    assert set(got) == {*range(100, 161), *range(500, 560)}
    assert all(c == (100 if n < 200 else 500) for n, c in got.items())
    assert connected_components(spark.createDataFrame([], "a long, b long")).count() == 0


def test_sorted_groups_hold_a_portion_at_a_time():
    import pyarrow as pa

    from raydescent.llm.common import sorted_groups

    rng = np.random.default_rng(0)
    keys = np.sort(rng.integers(0, 300, 5000))
    second = np.arange(5000) // 7
    read = []

    def batches():
        for at in [0, *range(0, 5000, 61)]:
            read.append(at)
            size = 0 if len(read) == 1 else 61
            yield pa.RecordBatch.from_pydict({"k": keys[at : at + size], "s": second[at : at + size], "v": np.arange(5000)[at : at + size]})

    for names, least in ((["k"], 1), (["k", "s"], 1), (["k"], 200), (["k"], 10**6)):
        read.clear()
        seen, ends = [], []
        for t in sorted_groups(batches(), names, least):
            v = t.column("v").to_pylist()
            assert least == 10**6 or len(v) < least + 100
            assert least == 10**6 or 61 * len(read) <= v[-1] + 200  # batches stream past, nothing is read ahead
            seen += v
            ends.append(tuple(int(c[v[-1]]) for c in (keys, second)[: len(names)]))
        assert seen == list(range(5000)) and len(set(ends)) == len(ends)
        if least == 1:
            assert len(ends) == len({tuple(int(c[i]) for c in (keys, second)[: len(names)]) for i in range(5000)})


def test_near_copies_among_boilerplate(spark):
    """Three thousand pages that share three quarters of their words, and a hundred planted copies."""
    from raydescent.llm.simhash_dedup import near_dedup

    rng = random.Random(21)
    page = [f"b{i}" for i in range(300)]
    own = lambda n: [f"w{rng.randrange(10**9)}" for _ in range(n)]
    pages = [page + own(40) for _ in range(3000)]
    texts = pages + [p[:-1] + own(1) if i % 2 else p[:100] + own(1) + p[101:] for i, p in enumerate(pages[:100])]
    texts = [" ".join(t) for t in texts]
    got = {r.doc_id for r in near_dedup(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(8), least=0.9, cosine=False).collect()}
    gone = set(range(3100)) - got
    assert len(gone & set(range(3000, 3100))) >= 95 and not gone & set(range(3000))


def test_near_copies_of_a_table_against_brute_force(spark):
    from raydescent.llm.simhash_dedup import near_dedup

    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    rows = sorted(texts_of(docs))
    for cosine in (True, False):
        want = {rows[i][0] for i in near_copies([t for _, t in rows], cosine=cosine)}
        gone = {i for i, _ in rows} - {r.doc_id for r in near_dedup(docs, cosine=cosine).collect()}
        assert gone <= want and len(gone) >= 0.95 * len(want)


# Packing


def test_plans_place_every_piece():
    from raydescent.llm.histogram_packing import plan_slots

    rng = random.Random(2)
    for _ in range(200):
        cap = rng.choice([5, 16, 64, 4096])
        counts = {rng.randint(1, cap): rng.randint(1, 60) for _ in range(rng.randint(1, 40))}
        held, rank = {}, Counter()
        for length, first_rank, many, first, offset in plan_slots(counts, cap):
            assert first_rank == rank[length]
            rank[length] += many
            for i in range(many):
                held.setdefault(first + i, []).append((offset, length))
        assert rank == Counter(counts) and sorted(held) == list(range(len(held)))
        for pieces in held.values():
            at = 0
            for offset, length in sorted(pieces):
                assert offset == at
                at += length
            assert at <= cap
        rooms, used = [], 0  # best fit decreasing, piece by piece
        for length in sorted(Counter(counts).elements(), reverse=True):
            fit = [r for r in rooms if r >= length]
            if fit:
                rooms.remove(min(fit))
                rooms.append(min(fit) - length)
            else:
                rooms.append(cap - length)
                used += 1
        assert len(held) == used
    with pytest.raises(ValueError):
        plan_slots({6: 1}, 5)


def test_packing(spark, odd, empty, tmp_path, monkeypatch):
    import zlib

    from tokenizers import Tokenizer

    from raydescent.llm import histogram_packing as m

    monkeypatch.setattr(m, "rank_parts", lambda n: 1 + n // 3)
    library = Tokenizer.from_file(WORD)
    got = m.pack_documents(odd.withColumnRenamed("source", "piece"), WORD)
    rows = got.collect()
    want = []
    for i, t in texts_of(odd):
        ids = [*library.encode(t or "", add_special_tokens=False).ids, 1]
        want += [(i is None, i or 0, p, 4096 * p, len(ids[4096 * p : 4096 * (p + 1)]), zlib.crc32(np.array(ids[4096 * p : 4096 * (p + 1)], "<u4").tobytes())) for p in range(-(-len(ids) // 4096))]
    assert sorted((r.doc_id is None, r.doc_id or 0, r.piece, r.start, r.length, r.ids_crc32) for r in rows) == sorted(want)
    by = {}
    for r in rows:
        by.setdefault(r.sequence_id, []).append((r.offset, r.length))
    for pieces in by.values():
        at = 0
        for offset, length in sorted(pieces):
            assert offset == at
            at += length
        assert at <= 4096
    assert m.pack_documents(empty, WORD).count() == 0
    few = odd.where("doc_id IN (0, 5, 7)")
    m.write_sequences(few, m.pack_documents(few, WORD), WORD, f"file://{tmp_path}/seq")
    written = sum(len(r.ids) for r in spark.read.parquet(f"file://{tmp_path}/seq").collect())
    assert written == sum(len(library.encode(t or "", add_special_tokens=False).ids) + 1 for i, t in texts_of(few))


def test_word_ids_on_every_latin_character():
    from raydescent.llm.bpe_automaton import read_vocabulary
    from raydescent.llm.histogram_packing import WordBpe

    bpe = WordBpe(read_vocabulary(WORD))
    rng = random.Random(4)
    texts = [f"a{chr(c)}B {chr(c)} 1{chr(c)}!" for c in range(0x300)]
    texts += ["".join(rng.choices([chr(c) for c in range(0x250)], k=rng.randint(0, 60))) for _ in range(2000)]
    texts += ["".join(rng.choices("aeINT'srelvmd 12.\n", k=rng.randint(0, 60))) for _ in range(2000)]
    for text in texts:
        assert np.frombuffer(bpe.encode(text), "<u4").tolist() == bpe.library.encode(text, add_special_tokens=False).ids, text


# Language model


def word_ids(*sizes):
    from raydescent.llm.backoff_lm import WordIds
    from raydescent.llm.bpe_automaton import read_vocabulary

    return WordIds(read_vocabulary(BYTE), *sizes)


def test_ids_of_whole_batches_equal_the_library(monkeypatch):
    """Words split and looked up a batch at once: contractions, white space of all kinds, text edges, other scripts, full slots."""
    import json

    import pyarrow as pa
    from tokenizers import Tokenizer

    from raydescent.llm import backoff_lm as m
    from raydescent.llm.bpe_automaton import read_vocabulary

    library = Tokenizer.from_str(json.dumps(json.loads(read_vocabulary(BYTE)) | {"added_tokens": []}))  # special tokens count as text
    few, rng = word_ids(300, 64), random.Random(12)

    def check(texts):
        flat, sizes = few.encode(pa.array(["'s not read", *texts], pa.string())[1:])
        assert [x.tolist() for x in np.split(flat, np.cumsum(sizes))[:-1]] == [library.encode(t or "", add_special_tokens=False).ids for t in texts]

    for alphabet in (" \t\n\xa0\x85é'st1.!rveldm", " \n\u3000\u180e\x1c\xa0aé日'st1.!", "'strevemlld a", "\U0001f600\u024f\u0250Éa '"):
        for most in (4_000_000, 40):  # bytes that are split at once
            monkeypatch.setattr(m, "AT_ONCE", most)
            for _ in range(60):
                check([None if rng.random() < 0.1 else "".join(rng.choices(alphabet, k=rng.randint(0, 12))) for _ in range(40)])
    check([f"a{c} {c}b {c} {c}{c} 1{c} {c}'s a" for c in map(chr, range(0x300))])
    check(["x" * 7, "x" * 8, "x" * 9, "x" * 15, "x" * 16, "x" * 70, "\0", "\0\0", "<|endoftext|>", "qzjxkvw" * 2] * 2)
    check([])
    check([None, ""])


def test_words_of_a_batch_are_looked_up_at_once():
    """A word is merged once, and does not come to the dictionary again while its slot holds it."""
    import pyarrow as pa

    held, asked = word_ids(), []
    merged = held.merged
    held.merged = lambda word: (asked.append(word), merged(word))[1]
    texts = pa.array([" ".join(f"w{chr(97 + i % 26)}{chr(97 + i // 26)}" for i in range(300))] * 20)
    first = held.encode(texts)
    assert len(asked) == len(set(asked)) == len(held) == 300
    held.clear()
    asked.clear()
    again = held.encode(texts)
    assert len(asked) < 10 and np.array_equal(first[0], again[0]) and np.array_equal(first[1], again[1])  # but for words whose slots others took


def test_ids_of_new_words_cost_less_than_by_the_automaton():
    """CPU seconds for documents whose words are mostly their own, with nothing remembered before."""
    import pickle
    import time

    import pyarrow.parquet as pq

    from raydescent.llm.bpe_automaton import compiled, read_vocabulary

    texts = pq.read_table("/root/testdata/sf0.01/documents.parquet", columns=["text"]).column("text").combine_chunks()
    texts = texts if hasattr(texts, "buffers") else texts.chunk(0)
    ours, bpe, took = word_ids(), pickle.loads(pickle.dumps(compiled(read_vocabulary(BYTE), True))), []
    for f in (lambda: b"".join(ours.encode(texts.slice(i, 200))[0].tobytes() for i in range(0, len(texts), 200)), lambda: b"".join(bpe.encode(t or "") for t in texts.to_pylist())):
        began = time.process_time()
        ids = f()
        took.append((time.process_time() - began, np.frombuffer(ids, "<u4" if took else "<u2").tolist()))
    assert took[0][1] == took[1][1] and took[0][0] < 0.7 * took[1][0], (took[0][0], took[1][0])


def test_backoff_scores(spark, data, odd, empty, monkeypatch):
    from raydescent.llm import backoff_lm as m
    from raydescent.llm.bpe_automaton import compiled, read_vocabulary

    monkeypatch.setattr(m, "CHUNK_TOKENS", 500)
    bpe = compiled(read_vocabulary(BYTE), True)
    docs = odd.select("doc_id", "text").union(table(spark, data, "documents").selectExpr("doc_id + 1000", "text"))
    ids = [(i, np.frombuffer(bpe.encode(t or ""), "<u4").tolist()) for i, t in texts_of(docs)]
    counts = [None, Counter(), Counter(), Counter()]
    for _, x in ids:
        for n in (1, 2, 3):
            counts[n].update(tuple(x[i : i + n]) for i in range(len(x) - n + 1))
    total = sum(counts[1].values())

    def score(x, i):
        for n in (3, 2):
            g = tuple(x[i - n + 1 : i + 1])
            if i >= n - 1 and counts[n][g] >= 2:
                return math.log(counts[n][g] / counts[n - 1][g[:-1]]) + (min(3, i + 1) - n) * math.log(0.4)
        return math.log(counts[1][(x[i],)] / total) + (min(3, i + 1) - 1) * math.log(0.4)

    got = m.backoff_scores(docs, BYTE, least=2).collect()
    assert len(got) == len(ids)
    want = sorted((i is None, i or 0, len(x), round(sum(score(x, j) for j in range(len(x))), 4)) for i, x in ids)
    for g, w in zip(sorted((r.doc_id is None, r.doc_id or 0, r.n_tokens, r.log_score) for r in got), want):
        assert g[:3] == w[:3] and abs(g[3] - w[3]) < 1e-3
    assert all((r.mean_log_score is None) == (r.n_tokens == 0) for r in got)
    assert m.backoff_scores(empty, BYTE).count() == 0


def test_backoff_scores_with_ngrams_seen_once(spark, data, monkeypatch):
    from raydescent.llm import backoff_lm as m
    from raydescent.llm.bpe_automaton import compiled, read_vocabulary
    from raydescent.llm.queries import op9_stupid_backoff

    monkeypatch.setattr(m, "CHUNK_TOKENS", 500)
    bpe = compiled(read_vocabulary(BYTE), True)
    ids = {i: np.frombuffer(bpe.encode(t or ""), "<u4").tolist() for i, t in texts_of(table(spark, data, "documents"))}
    counts = [None, Counter(), Counter(), Counter()]
    for x in ids.values():
        for n in (1, 2, 3):
            counts[n].update(tuple(x[i : i + n]) for i in range(len(x) - n + 1))
    total = sum(counts[1].values())

    def score(x, i):
        if i == 0:
            return math.log(counts[1][(x[0],)] / total)
        g = tuple(x[max(0, i - 2) : i + 1])  # every n-gram of the corpus itself is counted: nothing is given up
        return math.log(counts[len(g)][g] / counts[len(g) - 1][g[:-1]])

    got = {r.doc_id: r.log_score for r in op9_stupid_backoff(spark, data).collect()}
    assert got.keys() == ids.keys()
    for i, x in ids.items():
        assert abs(got[i] - sum(score(x, j) for j in range(len(x)))) < 1e-3


def test_backoff_scores_of_order_five(spark, empty):
    """Keys of 128 bits: five-grams of a vocabulary of 50,000."""
    from raydescent.llm import backoff_lm as m
    from raydescent.llm.bpe_automaton import compiled, read_vocabulary

    rng = random.Random(3)
    texts = [" ".join(rng.choices(["the", "cat", "sat", "on", "a", "mat"], k=rng.randint(0, 60))) for _ in range(60)]
    bpe = compiled(read_vocabulary(BYTE), True)
    ids = [np.frombuffer(bpe.encode(t), "<u4").tolist() for t in texts]
    assert m.key_kind(5, 50_257) == m.WIDE and m.key_kind(4, 50_257) != m.WIDE
    counts = {n: Counter(tuple(x[i : i + n]) for x in ids for i in range(len(x) - n + 1)) for n in range(1, 6)}
    total = sum(counts[1].values())
    for least in (1, 3):
        known = {n: {g: c for g, c in counts[n].items() if n == 1 or c >= least} for n in counts}

        def score(x, i):
            longest = min(5, i + 1)
            for n in range(longest, 0, -1):
                g = tuple(x[i - n + 1 : i + 1])
                if g in known[n] and (n == 1 or g[:-1] in known[n - 1]):
                    return math.log(known[n][g] / (known[n - 1][g[:-1]] if n > 1 else total)) + (longest - n) * math.log(0.4)

        got = {r.doc_id: r for r in m.backoff_scores(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string").repartition(3), BYTE, top=5, least=least).collect()}
        for i, x in enumerate(ids):
            assert abs(got[i].log_score - sum(score(x, j) for j in range(len(x)))) < 1e-6
        if least > 1:
            continue
        for i, x in enumerate(ids):  # by the counts of all other texts
            rest = {n: counts[n] - Counter(tuple(x[j : j + n]) for j in range(len(x) - n + 1)) for n in counts}
            want = 0.0
            for j in range(len(x)):
                longest = min(5, j + 1)
                n = next((n for n in range(longest, 1, -1) if rest[n][tuple(x[j - n + 1 : j + 1])] > 0), 1)
                g = tuple(x[j - n + 1 : j + 1])
                want += math.log(rest[n][g] / rest[n - 1][g[:-1]] if n > 1 else max(rest[1][g], 1) / max(total - len(x), 1)) + (longest - n) * math.log(0.4)
            assert abs(got[i].others_log_score - want) < 1e-6


def test_scores_by_others_tell_copies(spark):
    """A text that stands twice in the corpus is likely by the rest of it, a text that stands once is not."""
    from raydescent.llm.backoff_lm import backoff_scores

    rng = random.Random(5)
    texts = [" ".join(rng.choice("abcdefghijklmnopqrstuvwxyz") + str(rng.randrange(100)) for _ in range(80)) for _ in range(60)]
    got = {r.doc_id: r for r in backoff_scores(spark.createDataFrame(list(enumerate(texts + texts[:10])), "doc_id long, text string").repartition(3), BYTE).collect()}
    assert min(got[i].mean_others_log_score for i in (*range(10), *range(60, 70))) > max(got[i].mean_others_log_score for i in range(10, 60)) + 1


def test_packed_numbers():
    from raydescent.llm.backoff_lm import WIDE, mix, pack, unpack

    wide = np.sort(np.array([b"\0" * 16, b"a" * 16, b"\0" * 15 + b"\1", b"\1" + b"\0" * 15], WIDE))
    assert np.array_equal(unpack(pack(wide), WIDE), wide) and len(set(mix(wide).tolist())) == 4
    assert [int.from_bytes(x.ljust(16, b"\0"), "big") for x in wide.tolist()] == sorted(int.from_bytes(x.ljust(16, b"\0"), "big") for x in wide.tolist())

    x = np.array([0, 1, 2**63, 2**64 - 1, 12345], np.uint64)
    assert np.array_equal(unpack(pack(x)), x) and len(unpack(pack(x[:0]))) == 0


# Language


def test_language(spark, data, odd, empty):
    from pyspark.sql import functions as F

    from raydescent.llm.language_bayes import fit, learned_rows, predict

    docs = spark.read.parquet(f"{data.replace('0.001', '0.1')}/documents.parquet").select("doc_id", "text", "lang")
    model = fit(docs.where(learned_rows(F.col("doc_id"))), most_rows=1500)
    held = predict(docs.where(~learned_rows(F.col("doc_id"))), model).collect()
    assert sum(r.lang == r.lang_pred for r in held) / len(held) >= 0.98
    got = {r.doc_id: r for r in predict(odd.withColumnRenamed("source", "score"), model).collect()}
    assert [got[i].lang_pred for i in (0, 1, 2, 3)] == ["und"] * 4 and got[4].lang_pred == "en"
    assert all(0 <= r.score <= 1 for r in got.values())
    assert predict(empty, model).count() == 0
    assert {r.lang_pred for r in predict(odd, fit(empty)).collect()} == {"und"}


def test_language_scores_against_brute_force(spark):
    """Counts, probabilities and posterior shares from their definitions, gram by gram."""
    from raydescent.llm.language_bayes import fit, has_letter, identify

    rng = random.Random(7)
    train = [(i, "".join(rng.choices("abcdeé " if i % 2 else "xyzßa ", k=rng.randint(0, 40))), "AB"[i % 2]) for i in range(60)] + [(90, None, "A"), (91, "zzz", None)]
    model = fit(spark.createDataFrame(train, "doc_id long, text string, lang string").repartition(3), buckets=1 << 8)

    def grams(text):
        for n in (2, 3):
            for i in range(len(text) - n + 1):
                h = n
                for c in text[i : i + n]:
                    h = (h ^ ord(c)) * 0x9E3779B1 & 0xFFFFFFFF
                    h ^= h >> 15
                yield h & 255

    counts = {x: Counter(g for _, t, lang in train if lang == x and t is not None for g in grams(t.lower())) for x in "AB"}
    sums = {x: sum(c.values()) for x, c in counts.items()}
    texts = ["abc", "zyx ß", "", "ab" * 700 + "é", "½ ²", "Ⅷ ①", "x", "ʰ", "Ab1", None, "aé xyz " * 3]
    want = []
    for t in texts:
        if t is None or not any(c.isalpha() for c in t):
            want.append(("und", 0.0))
            continue
        s = {x: sum(math.log((counts[x][g] + 0.5) / (sums[x] + 128)) for g in grams(t.lower())) for x in "AB"}
        best = max(s, key=s.get)
        want.append((best, 1 / sum(math.exp(v - s[best]) for v in s.values())))
    got = identify(texts, model)
    assert [g[0] for g in got] == [w[0] for w in want] and want[4][0] == want[5][0] == "und" != want[7][0]
    assert all(abs(g[1] - w[1]) < 1e-9 for g, w in zip(got, want))
    assert not has_letter("½²Ⅷ①12_ ") and has_letter("1ª")


def test_null_ids_are_learned_from(spark):
    from pyspark.sql import functions as F

    from raydescent.llm.language_bayes import learned_rows

    rows = spark.createDataFrame([(None,), (1,)], "doc_id long")
    assert [r.x for r in rows.select(learned_rows(F.col("doc_id")).alias("x")).collect()][0] is True


def test_letters_of_a_step_boundary():
    from raydescent.llm import language_bayes as m

    text = "".join(random.Random(1).choices("abcdef ", k=5000))
    whole = m.ngram_counts(text, (2, 3), 1 << 10)
    step, m._STEP = m._STEP, 97
    try:
        assert np.array_equal(m.ngram_counts(text, (2, 3), 1 << 10), whole)
    finally:
        m._STEP = step
