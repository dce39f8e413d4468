import hashlib
import random
import zlib

import numpy as np
import public_tokenizers
import pytest
import xxhash
from pyspark.sql import functions as F
from tokenizers import Tokenizer

from regionfilter.llm import bpe, chat, exact_dedup, html_text, licenses, packing, quality, queries, simhash, token_counts, topk
from regionfilter.llm.bpe_roundtrip import decode_ids, encode_texts, roundtrip_digests
from regionfilter.llm.common import distinct_texts, table

LIBRARY = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json"))
HARD = ["", None, " ", "a", "a", "A  b\n\nc", "<|endoftext|> x<|endoftext|>", "'s're''ll", "日本語 text 😀", "x" * 9000, "ab1!" * 3000 + " tail", "　a\xa0 b\x1c c\x85\n", "word " * 3000]
SCHEMA = "doc_id long, text string, keep_id string, digest int, rank double"


@pytest.fixture(scope="module")
def hard(spark):
    """Nulls, empty and long texts, ties, repeated rows, and extra columns with clashing names."""
    rows = [(i, t, "x", i, 0.5) for i, t in enumerate(HARD)]
    return spark.createDataFrame([*rows, rows[3], (None, "lost", None, None, None)], SCHEMA)


@pytest.fixture(scope="module")
def none(spark):
    return spark.createDataFrame([], SCHEMA)


@pytest.mark.parametrize("name", list(queries.ORACLES))
def test_same_as_sql(name, spark, sf, same):
    same(queries.QUERIES[name](spark, sf), queries.ORACLES[name])


# ---- exact dedup
def test_exact_dedup(hard, none, spark):
    got = exact_dedup.verdicts(hard).collect()
    assert len(got) == len(HARD) + 2
    by = {r["doc_id"]: r for r in got}
    assert by[0]["keep_id"] == 1 and not by[0]["kept"] and by[1]["kept"] and by[0]["group_size"] == 2  # null is empty
    assert by[3]["group_size"] == 3 and by[3]["keep_id"] == 4
    assert by[0]["text_sha256"] == hashlib.sha256(b"").hexdigest()
    kept = exact_dedup.deduplicate(hard)
    assert kept.columns == hard.columns
    assert sorted(r["doc_id"] for r in kept.where("doc_id is not null").collect()) == [1, 2, 4, *range(5, len(HARD))]
    assert exact_dedup.verdicts(none).count() == 0 and exact_dedup.deduplicate(none).count() == 0
    twice = spark.createDataFrame([(1, "x"), (1, "y"), (5, "y"), (5, "y"), (7, None), (7, ""), (None, "q"), (None, "q")], "doc_id long, text string")
    assert sorted((r["doc_id"] or 0, r["text"] or "") for r in exact_dedup.deduplicate(twice).collect()) == [(0, "q"), (1, "x"), (5, "y"), (7, "")]
    small = {r["keep_id"] for r in exact_dedup.verdicts(hard, "smallest").where("doc_id = 4").collect()}
    assert small == {3}


def test_runs_are_merged_in_order(spark):
    """As many rounds as the number of runs asks for; no round has a hash step."""
    docs = spark.range(3000).select((F.col("id") % 1700).alias("doc_id"), F.concat(F.lit("t"), (F.col("id") % 900).cast("string")).alias("text")).repartition(70)
    runs = exact_dedup.sorted_runs(docs)
    level = runs.select(F.col("run").alias("node"), "slice", *exact_dedup.KEY, F.col("doc_id").alias("keep_id"), F.lit(1).cast("long").alias("group_size"))
    plan = exact_dedup.merge_round(level, "largest", 2)._jdf.queryExecution().executedPlan().toString()
    assert "SortAggregate" in plan and "HashAggregate" not in plan
    for keep, best in (("largest", max), ("smallest", min)):
        got = {r["keep_id"]: r["group_size"] for r in exact_dedup.merge_runs(runs, keep, fan_bits=2).collect()}
        want = {}
        for i in range(3000):
            want.setdefault(i % 900, []).append(i % 1700)
        assert sorted((best(v), len(v)) for v in want.values()) == sorted((r["keep_id"], r["group_size"]) for r in exact_dedup.merge_runs(runs, keep, fan_bits=2).collect()) and got


# ---- encoder
def test_encoder_against_the_library():
    rng = random.Random(3)
    parts = ["abc", "the", "'s", "'re", "  ", " ", "\n", "\t\n", "\xa0", "　", "é", "日本", "😀", "123", "²", "!!", "<|endoftext|>", "<|endof", "\x1c", "\x85", "''", "​", "ﬁ"]
    solid = ["ab", "c", "the", "é", "日", "'s", "1", "!", "ing"]
    enc = bpe.Encoder(leaf=16)
    for i in range(1500):
        s = "".join(rng.choice(parts if i % 2 else solid) for _ in range(rng.randint(0, 80)))
        assert enc.encode(s) == LIBRARY.encode(s, add_special_tokens=False).ids, repr(s)
        assert np.frombuffer(enc.encode_tree(s)[0], dtype="<u4").tolist() == enc.encode(s), repr(s)
        assert enc.decode(enc.encode(s)) == s


def test_long_text_without_spaces():
    enc = bpe.Encoder(leaf=256)
    for s in ("a" * 5000, "abcdefghij" * 900, "日本語" * 1500, "0123456789" * 500, "-=" * 3000):
        assert enc.encode(s) == LIBRARY.encode(s, add_special_tokens=False).ids
        assert enc.encode_tree(s)[1] >= len(s) // 256


@pytest.mark.parametrize("leaf", [64, 1024])
def test_whole_documents_go_through_the_tree(spark, sf, leaf):
    """Every text of the given table, whole, by the tree and by the library alone."""
    texts = [r["text"] or "" for r in table(spark, sf, "documents").collect()]
    enc, joins = bpe.Encoder(leaf=leaf), 0
    for t, e in zip(texts, LIBRARY.encode_batch_fast(texts, add_special_tokens=False), strict=True):
        ids, made = enc.encode_tree(t)
        assert np.frombuffer(ids, dtype="<u4").tolist() == e.ids
        joins += made
        assert made >= len(t) // (leaf + 1) - 1
    assert joins > len(texts)
    flat = enc.encode_many(texts)
    assert [len(x) // 4 for x in flat] == [len(enc.encode_tree(t)[0]) // 4 for t in texts]


def test_roundtrip_and_counts_of_all_documents(spark, sf):
    texts = {r["doc_id"]: r["text"] or "" for r in table(spark, sf, "documents").collect()}
    want = dict(zip(texts, (e.ids for e in LIBRARY.encode_batch_fast(list(texts.values()), add_special_tokens=False))))
    for r in queries.QUERIES["op7_bpe_roundtrip"](spark, sf).collect():
        ids = want[r["doc_id"]]
        assert (r["n_tokens"], r["ids_sha256"]) == (len(ids), hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest())
        assert r["decoded_sha256"] == hashlib.sha256(LIBRARY.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    for r in queries.QUERIES["op4_token_counts"](spark, sf).collect():
        assert (r["n_bytes"], r["n_tokens"], r["over_limit"]) == (len(texts[r["doc_id"]].encode()), len(want[r["doc_id"]]), len(want[r["doc_id"]]) > 1024)
    total = 0
    for r in queries.QUERIES["op6_packing"](spark, sf).collect():
        ids = [*want[r["doc_id"]], 0]
        assert r["ids_crc32"] == zlib.crc32(np.array(ids[r["start"] : r["start"] + r["length"]], dtype="<u4").tobytes()) and r["doc_tokens"] == len(ids)
        total += r["length"]
    assert total == sum(len(x) + 1 for x in want.values())


def test_roundtrip(hard, none, spark):
    got = {r["doc_id"]: r for r in roundtrip_digests(hard).collect()}
    for i, t in enumerate(HARD):
        ids = LIBRARY.encode(t or "", add_special_tokens=False).ids
        assert got[i]["n_tokens"] == len(ids)
        assert got[i]["ids_sha256"] == hashlib.sha256(",".join(map(str, ids)).encode()).hexdigest()
        assert got[i]["decoded_sha256"] == hashlib.sha256(LIBRARY.decode(ids, skip_special_tokens=False).encode()).hexdigest()
    texts = distinct_texts(hard)
    back = decode_ids(encode_texts(texts))
    assert back.join(texts.withColumnRenamed("text", "was"), "digest").where("text <> was").count() == 0
    assert roundtrip_digests(none).count() == 0


# ---- token counts
def test_token_counts_and_cache(hard, none, spark, tmp_path):
    at = f"file://{tmp_path}/cache"
    want = {i: len(LIBRARY.encode(t or "", add_special_tokens=False).ids) for i, t in enumerate(HARD)}
    first = {r["doc_id"]: r["n_tokens"] for r in token_counts.token_counts(hard, cache_folder=at).collect()}
    assert {i: first[i] for i in want} == want
    cache = token_counts.CountCache(spark, at)
    n = cache.stored().count()
    more = hard.select("doc_id", "text").unionByName(spark.createDataFrame([(99, "something new")], "doc_id long, text string"))
    again = {r["doc_id"]: (r["n_tokens"], r["over_limit"]) for r in token_counts.token_counts(more, limit=2, cache_folder=at).collect()}
    assert cache.stored().count() == n + 1 and again[99] == (2, False) and again[12][1]
    assert token_counts.token_counts(none).count() == 0


# ---- packing
def _best_fit(counts, window):
    """One piece at a time into the tightest open window."""
    open_ = []
    for length in sorted((x for x, n in counts.items() for _ in range(n)), reverse=True):
        fit = [r for r in open_ if r >= length]
        if fit:
            open_.remove(min(fit))
            open_.append(min(fit) - length)
        else:
            open_.append(window - length)
    return sorted(open_)


def test_plan_is_best_fit_decreasing():
    rng = random.Random(5)
    for _ in range(60):
        window = rng.choice([8, 16, 37])
        counts = {rng.randint(1, window): rng.randint(1, 9) for _ in range(rng.randint(1, 12))}
        plan, n = packing.plan_windows(counts, window)
        used = [0] * n
        for length, first, last, per, seq, offset in plan:
            for i in range(first, last):
                assert used[seq + (i - first) // per] == offset + (i - first) % per * length
                used[seq + (i - first) // per] += length
        assert sorted(window - u for u in used) == _best_fit(counts, window)
        assert {x: sum(p[2] - p[1] for p in plan if p[0] == x) for x in counts} == counts


def test_packing(hard, none):
    rows = packing.pack(hard).collect()
    by_doc, by_seq = {}, {}
    for r in rows:
        by_doc.setdefault(r["doc_id"], []).append(r)
        by_seq.setdefault(r["sequence_id"], []).append((r["offset"], r["length"]))
    for i, t in enumerate(HARD):
        ids = [*LIBRARY.encode(t or "", add_special_tokens=False).ids, 0]
        pieces = sorted({(r["start"], r["length"], r["ids_crc32"], r["doc_tokens"]) for r in by_doc[i]})
        assert sum(p[1] for p in pieces) == len(ids)
        for start, length, crc, n in pieces:
            assert n == len(ids) and crc == zlib.crc32(np.array(ids[start : start + length], dtype="<u4").tobytes())
    for spans in by_seq.values():
        at = 0
        for offset, length in sorted(spans):
            assert offset == at
            at += length
        assert at <= 1024
    assert packing.pack(none).count() == 0


# ---- simhash
def _plain_fingerprint(text):
    words = [w for w in __import__("re").split(r"[\x20\x09-\x0D]+", "".join(c.lower() if "A" <= c <= "Z" else c for c in text)) if w]
    shingles = [" ".join(words[i : i + 3]) for i in range(max(1, len(words) - 2))] if words else []
    h = [xxhash.xxh64_intdigest(s.encode(), 42) for s in shingles]
    return sum(1 << b for b in range(64) if 2 * sum(x >> b & 1 for x in h) > len(h)) if h else 0


def _plain_components(fps):
    parent = list(range(len(fps)))

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for i in range(len(fps)):
        for j in range(i):
            if bin(fps[i][1] ^ fps[j][1]).count("1") <= 2:
                a, b = find(i), find(j)
                parent[max(a, b)] = min(a, b)
    ids = {}
    for i, (doc, _) in enumerate(fps):
        ids.setdefault(find(i), []).append(doc)
    return {doc: min(v) for v in ids.values() for doc in v}


def test_simhash_against_brute_force(spark, sf):
    docs = table(spark, sf, "documents").select("doc_id", "text").collect()
    fps = [(r["doc_id"], _plain_fingerprint(r["text"] or "")) for r in docs]
    want = _plain_components(fps)
    got = {r["doc_id"]: r for r in simhash.op10_simhash(spark, sf).collect()}
    assert {d: f"{fp:016x}" for d, fp in fps} == {d: r["fingerprint"] for d, r in got.items()}
    assert want == {d: r["component_id"] for d, r in got.items()}


@pytest.mark.parametrize("crowded", [1, 3, 64])
def test_links_and_chains(spark, crowded):
    rng = random.Random(crowded)
    fps = [rng.getrandbits(64) for _ in range(30)]
    for base in list(fps[:6]):
        x = base
        for _ in range(12):  # chains and crowded halves
            x ^= 1 << rng.randrange(64)
            x ^= 1 << rng.randrange(32)
            fps.append(x)
    fps = sorted(set(fps) | {0, 3, (1 << 63), (1 << 63) | 1})
    signed = [x - (1 << 64) if x >> 63 else x for x in fps]
    nodes = spark.createDataFrame([(x,) for x in signed], "fp long")
    got = {(r["a"], r["b"]) for r in simhash.links(nodes, crowded).collect()}
    want = {(min(a, b), max(a, b)) for i, a in enumerate(signed) for b in signed[:i] if bin((a ^ b) & (1 << 64) - 1).count("1") <= 2}
    assert got == want
    ids = nodes.withColumn("id", F.row_number().over(__import__("pyspark.sql", fromlist=["Window"]).Window.orderBy(F.xxhash64("fp"))).cast("long"))
    edges = simhash.links(nodes, crowded)
    number = {r["fp"]: r["id"] for r in ids.collect()}
    label = {r["fp"]: r["component"] for r in simhash.components(edges, ids).collect()}
    parent = {x: x for x in signed}

    def find(x):
        while parent[x] != x:
            x = parent[x]
        return x

    for a, b in want:
        parent[find(a)] = find(b)
    groups = {}
    for x in signed:
        groups.setdefault(find(x), []).append(number[x])
    for x in {y for e in want for y in e}:
        assert label[x] == min(groups[find(x)])


def test_simhash_edges(hard, none, spark, monkeypatch):
    got = {r["doc_id"]: r for r in simhash.near_groups(hard).collect()}
    assert got[0]["fingerprint"] == "0" * 16 and {got[i]["component_id"] for i in (0, 1, 2)} == {0}
    assert got[3]["component_id"] == 3 and got[4]["component_id"] == 3
    assert simhash.near_groups(none).count() == 0
    chain = spark.createDataFrame([(None, "a"), (5, "b"), (9, "c"), (None, "z")], "doc_id long, text string")
    given = {"a": 1, "b": 3, "c": 15, "z": 255 << 40}
    monkeypatch.setattr(simhash, "fingerprints", lambda docs, shingle: docs.select("doc_id", F.create_map(*(F.lit(x) for kv in given.items() for x in kv))[F.col("text")].cast("long").alias("fp")))
    assert sorted((r["doc_id"] or 0, r["component_id"]) for r in simhash.near_groups(chain).where("component_id is not null").collect()) == [(0, 5), (5, 5), (9, 5)]
    assert simhash.near_groups(chain).where("component_id is null and doc_id is null").count() == 1


# ---- top-k
def test_topk_edges(spark):
    nan = float("nan")
    rows = [(0, [1.0, 0.5]), (50, [0.25, 0.25]), (50, [0.5, 0.5]), (1, None), (2, [None, 1.0]), (3, [nan, 1.0]), (4, [1.0, 0.5]), (5, [1.0, 0.5]), (6, [-1.0, 0.0]), (7, []), (None, [1.0, 1.0])]
    v = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    got = topk.top_k(v, F.col("vec_id") % 50 == 0, 3).collect()
    usable = [(i, [int(np.floor(256 * x)) for x in e]) for i, e in rows if i is not None and e is not None and all(x is not None and x == x for x in e)]
    mine = sorted((r["rank"], r["vec_id"], r["score"]) for r in got if r["query_id"] == 0)
    want = sorted(((-sum(a * b for a, b in zip([256, 128], e)), i) for i, e in usable if i != 0))[:3]
    assert mine == [(k + 1, i, -s) for k, (s, i) in enumerate(want)]
    assert topk.top_k(v.where("false"), F.col("vec_id") % 50 == 0).count() == 0
    clash = v.select("*", *(F.lit(1).alias(c) for c in ("query", "norm", "grp", "v", "score", "rank", "block")))
    assert sorted(map(tuple, topk.top_k(clash, F.col("vec_id") % 50 == 0, 3).collect())) == sorted(map(tuple, got))
    few = topk.top_k(v.where("vec_id in (0, 4)"), F.col("vec_id") % 50 == 0, 5).collect()
    assert [(r["query_id"], r["rank"], r["vec_id"]) for r in few] == [(0, 1, 4)]


@pytest.mark.parametrize("most", [3, 1024])
def test_topk_in_groups_and_with_a_common_vector(spark, monkeypatch, most):
    monkeypatch.setattr(topk, "GROUP", most)
    rng = np.random.default_rng(3)
    rows = [(i, [1.0, -2.0, 0.5] if i % 3 == 0 else rng.normal(size=3).tolist()) for i in range(600)]
    rows += [(50, [1.0, 1.0, 1.0])] * 40 + [(7, [9.0, 9.0, 9.0])] * 40  # one id and vector many times
    got = {}
    for r in topk.top_k(spark.createDataFrame(rows, "vec_id long, embedding array<double>"), F.col("vec_id") % 50 == 0).collect():
        got.setdefault(r["query_id"], []).append((r["rank"], r["vec_id"], r["score"]))
    whole = [(i, [int(np.floor(256 * x)) for x in e]) for i, e in rows]
    for q in range(0, 600, 50):
        asks = {tuple(v) for i, v in whole if i == q}
        best = sorted((-sum(a * b for a, b in zip(x, v)), i) for x in asks for i, v in whole if i != q)[:5]
        assert sorted(got[q]) == [(k + 1, i, -s) for k, (s, i) in enumerate(best)]


# ---- chat
def test_template_compiler():
    text, spans = chat.render([{"role": "user", "text": "</s>[INST] \\l"}, {"role": "assistant", "text": "ok<"}])
    assert text == "<s>user[INST]\\l/s>\\bINST] \\\\l[/INST]</s><s>assistant[INST]ok\\l[/INST]</s>"
    assert [text[a:b] for a, b in spans] == ["ok\\l"]
    for s in ("", "\\", "<s>[/INST]</s>", "\\l\\b\\\\", "[[<<"):
        assert chat.unescape(chat.escape(s)) == s and "<" not in chat.escape(s)
    folded = chat.fold(chat.parse("a{{ 'b' + 'c' }}{% if 1 == 1 %}d{% else %}{{ x }}{% endif %}{{ 2 + 3 }}"))
    assert folded == (chat.Output(chat.Const("abcd5")),)
    out = "".join(p for p, _ in chat.compile_template("{% for m in ms %}{% if not loop.first and m.n != 2 %}{{ m.n }}{% elif m['n'] == 2 %}two{% else %}-{% endif %}{% endfor %}")(ms=[{"n": i} for i in range(4)]))
    assert out == "-1two3"
    trimmed = "".join(p for p, _ in chat.compile_template("x {%- if 1 == 1 -%} y {{- z -}}  w {% endif %}")(z="!"))
    assert trimmed == "xy!w "
    for bad in ("{{ x.__class__ }}", "{{ f() }}", "{% for x %}{% endfor %}", "{% if x %}", "{{ x | nope }}", "{% endif %}", "{{ 'a }}", "{% import os %}"):
        with pytest.raises(chat.TemplateError):
            chat.compile_template(bad)


def test_chat_edges(spark):
    rows = [(1, 1, "assistant", "b"), (1, 0, None, None), (1, 1, "assistant", "b"), (None, 0, "user", "x"), (2, None, "user", "z" * 100000)]
    got = {r["conv_id"]: r for r in chat.read_back(spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("n_turns", F.lit("clash"))).collect()}
    assert got[1]["n_turns"] == 3 and got[1]["loss_chars"] == 2
    assert got[1]["turns_sha256"] == hashlib.sha256(b"\n\nassistant\nb\nassistant\nb\n").hexdigest()
    assert got[None]["n_turns"] == 1 and got[2]["loss_sha256"] == hashlib.sha256(b"").hexdigest()
    assert chat.read_back(spark.createDataFrame([], "conv_id long, turn long, role string, text string")).count() == 0


# ---- html
def test_html():
    page = """<html><head><title>T</title><style>p{}</style><script>if(a<b){"</p>"}</script></head><body><header><h1>Site name</h1></header><nav><ul><li><a href=/>Home</a></li></ul></nav>
    <div class="cookie-notice">We use cookies, accept them all now please</div><main><article class="post"><h2>The   title</h2><p>First &amp; <b>bold</b>er paragraph&nbsp;of text with enough words.<br>Line two.</p>
    <div class="ad">Buy this thing now</div><p>Second paragraph <a href=x>with a link</a> inside.<form><input name=q><button>Send</button></form><ul><li>one item</li><li>two items</li></ul></article></main>
    <section id="comments"><h3>Comments</h3><p>A reader says that this is a long comment about everything in the text.</p></section><aside>Related posts</aside><footer><p>All rights reserved</p></footer></body></html>"""
    assert html_text.extract(page) == "The title\n\nFirst & bolder paragraph of text with enough words. Line two.\n\nSecond paragraph with a link inside.\n\none item\n\ntwo items"
    assert html_text.extract(None) == "" == html_text.extract("") == html_text.extract("<nav>x</nav>")
    assert html_text.extract("just words & <b>more") == "just words & more"
    bare = "<body><div class=menu><a href=1>A</a> <a href=2>B</a></div><div><p>" + "real content words " * 20 + "</p><p>more of it</p></div><div class=sidebar><a href=3>C</a></div></body>"
    assert html_text.extract(bare) == " ".join(["real content words"] * 20) + "\n\nmore of it"
    for broken in ("<", "<p", "<p class='x", "<!-- never", "</div></p>text", "<script>never", "a < b and c > d", "<p>" * 3000 + "deep"):
        assert isinstance(html_text.extract(broken), str)


def test_html_on_given_pages(spark, sf):
    import html
    import re

    got = {r["page_id"]: r["text"] for r in html_text.op3_html_text(spark, sf).collect()}
    for r in table(spark, sf, "pages").collect():
        body = re.search(r"<article>(.*?)</article>", r["html"], re.S)[1].replace("<br>", " ")
        want = [" ".join(html.unescape(re.sub(r"<[^>]+>", "", b)).split()) for b in re.split(r"</?(?:h1|p)>", body)]
        assert got[r["page_id"]] == "\n\n".join(b for b in want if b)


def test_best_stretch_is_the_best():
    rng = random.Random(9)
    for _ in range(300):
        s = [rng.randint(-4, 4) for _ in range(rng.randint(0, 12))]
        a, b = html_text.best_stretch(s)
        assert sum(s[a:b]) == max([0] + [sum(s[i:j]) for i in range(len(s)) for j in range(i + 1, len(s) + 1)])


# ---- licenses
def test_licenses_against_brute_force(spark, sf):
    t = licenses.Templates()

    def plain(text):
        best = None
        for unit in {text, *text.split("\n"), *__import__("re").split(r"\n[ \t]*\n\s*", text)}:
            u = licenses.bigrams(unit)
            for _, name, g in t.items:
                d = 2 * len(u & g) / (len(u) + len(g)) if u else 0
                if d >= licenses.LEAST - 1e-12 and (best is None or (-d, name) < best):
                    best = (-d, name)
        return best and best[1]

    docs = {r["doc_id"]: r["text"] or "" for r in table(spark, sf, "documents").collect()}
    docs |= {-1: "MIT License\n\nCopyright (c) 2020 A\n\n" + licenses.TEXTS["MIT"], -2: licenses.TEXTS["MIT"].upper(), -3: "Licensed under CC BY-NC-SA 4.0.", -4: "license"}
    got = {r["doc_id"]: r for r in licenses.scanned(spark.createDataFrame(list(docs.items()), "doc_id long, text string")).collect()}
    assert {d: plain(x) for d, x in docs.items()} == {d: r["license"] for d, r in got.items()}
    assert got[-2]["license"] == "MIT" and got[-2]["dice"] == 1.0 and got[-3]["license"] is None
    assert any(r["license"] for d, r in got.items() if d >= 0)


def test_licenses_edges(hard, none):
    assert licenses.scanned(hard).where("license is not null or n_notices > 0").count() == 0
    assert licenses.scanned(none).count() == 0


# ---- quality
def test_quality(spark, hard, none):
    sf = "/root/testdata/sf0.01"
    labels = table(spark, sf, "labels")
    got = {r["doc_id"]: r for r in quality.op9_quality(spark, sf).collect()}
    known = [(r["doc_id"], r["quality"]) for r in labels.collect()]
    held = [(got[d]["predicted"], y) for d, y in known if d in got and got[d]["held_out"]]
    assert all(got[d]["held_out"] == (zlib.crc32(str(d).encode()) % 3 == 1) for d, _ in known if d in got)
    assert len(held) > 80 and sum(p == y for p, y in held) / len(held) > 0.97
    odd = quality.scored(hard, labels.limit(0))
    assert {r["score"] for r in odd.collect()} == {0.5} and odd.count() == len(HARD) + 2
    assert quality.scored(none, labels).count() == 0 and quality.keep_good(none, labels).columns == none.columns
