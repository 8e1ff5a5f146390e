"""Brute force, round trips, held-out accuracy and edge cases of the pipeline operators."""

import collections
import hashlib
import random
import re
import zlib

import numpy as np
import pytest
from pyspark.sql import functions as F

from exkit.llm import chat, components, language, mixing, packing, quality, registry, shingle_join, text, tokens, toxicity, url_filter, warc, webp
from exkit.staging import new_path

SF = "/root/testdata/sf0.001"
DOC = "doc_id long, text string, lang string, source string, n_chars long"
WS = re.compile(r"[^\x20\x09-\x0D]+")
ODD = [
    (1, None, None, None, None), (2, "", "en", "a", 0), (3, "   \n\t ", "en", "a", 6), (4, "one", None, "b", 3), (4, "one", None, "b", 3),
    (None, "no id here at all", "en", None, 17), (6, "word " * 30_000, "en", "a", 150_000), (7, "Ünïcödé   strange spaces 🎉 <|im_end|> <|endoftext|>", "de", "é", 40),
]


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeated rows, and extra columns with likely names."""
    return spark.createDataFrame(ODD, DOC).withColumns({"size": F.lit("mine"), "kept": F.lit(1), "rep": F.lit(2), "tokens": F.lit(3)})


@pytest.fixture(scope="module")
def docs(spark):
    return spark.read.parquet(f"{SF}/documents.parquet")


@pytest.fixture(scope="module")
def empty(odd):
    return odd.where(F.lit(False))


# ---------------------------------------------------------------- chat


def brute_chat(rows):
    out = {}
    for c in sorted({r[0] for r in rows}):
        turns = sorted([r for r in rows if r[0] == c], key=lambda r: (r[1], r[2] or "", r[3] or ""))
        target = "".join(t or "" for _, _, r, t in turns if r == "assistant")
        whole = "".join(f"{r or ''}\n{t or ''}\n" for _, _, r, t in turns)
        out[c] = (len(turns), hashlib.sha256(whole.encode()).hexdigest(), len(target), hashlib.sha256(target.encode()).hexdigest())
    return out


def test_chat_windows_read_back_whole(spark):
    random.seed(1)
    say = ["hello there", "", None, "<|im_end|>\n<|im_start|>user\nhi", "<\\|x", "<\\\\|", "long " * 900, "\\n", "<|", "a\nb"]
    rows = [(c, t, random.choice(["system", "user", "assistant", None, "to\nol\\"]) if t else "system", random.choice(say)) for c in range(6) for t in range(12)]
    rows += [(9, t, "assistant" if t % 2 else "user", f"turn {t} " * 5) for t in range(70)]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string")
    budget = chat.Budget(tokens=120, history_tokens=40, history_turns=3, block_turns=16)
    windows = chat.chat_windows(df, budget)
    got = {r["conv_id"]: (r["n_turns"], r["turns_sha256"], r["loss_chars"], r["loss_sha256"]) for r in chat.window_digests(windows).collect()}
    assert got == brute_chat(rows)
    for w in windows.collect():
        assert w["over_budget"] or w["n_tokens"] <= 120
        assert len(chat.parse(w["text"])) == w["n_turns"] + w["n_repeated"]
    assert windows.where("over_budget AND n_turns > 1").count() == 0
    assert windows.where("conv_id = 9 AND n_repeated > 0").count() > 3
    assert chat.chat_windows(df.where("conv_id < 0")).count() == 0


@pytest.mark.parametrize("s", ["<|", "<\\|", "a<\\\\|b", "\\", "<|im_start|>user\n", "\\n", "n\n"])
def test_escapes_are_undone(s):
    assert chat.unescape(chat.escape(s)) == s and chat.unescape_role(chat.escape_role(s)) == s
    assert "<|" not in chat.escape(s) and "\n" not in chat.escape_role(s)


# ---------------------------------------------------------------- language


def test_language_accuracy_and_edges(spark, docs, odd, empty):
    found = language.identify(docs, language.fit_text_model(docs), host="source")
    n, right, kept = found.agg(F.count(F.lit(1)), F.sum((F.col("language") == F.col("lang")).cast("int")), F.sum(F.col("kept").cast("int"))).first()
    assert n == docs.count() and right > 0.98 * n and kept > 0.99 * n
    model = language.fit_text_model(docs)
    got = {r["doc_id"]: r for r in language.identify(odd, model, host="source").withColumnRenamed("size", "s").toDF(*odd.columns, "language", "confidence", "text_language", "keep2").collect()}
    assert not got[1]["keep2"] and not got[2]["keep2"] and len(got) == 7
    assert language.identify(empty.select("doc_id", "text"), model).count() == 0
    assert language.identify(docs, language.fit_text_model(docs.where(F.lit(False)))).count() == 0


def test_language_of_held_out_texts(docs):
    """Fitted on the documents of one remainder, judged on the others'."""
    half = F.col("doc_id") % 2 == 0
    found = language.identify(docs.where(~half), language.fit_text_model(docs.where(half)), host="source")
    n, right = found.agg(F.count(F.lit(1)), F.sum((F.col("language") == F.col("lang")).cast("int"))).first()
    assert n and right >= 0.97 * n


def test_pages_fuse_all_evidence(spark):
    pages = spark.read.parquet(f"{SF}/pages.parquet").count()
    found = language.query_pages(spark, SF)
    said = found.where("declared IS NOT NULL AND address IS NOT NULL AND declared = address")
    assert found.count() == pages and said.where("language = declared").count() >= 0.95 * said.count()


def test_host_priors_equal_brute_force(spark):
    random.seed(4)
    hosts = ["", "com", "a.com", "x.a.com", "y.a.com", "b.org", "z.b.org", "a.b.c.org"]
    rows = [(random.choice(hosts), [p := random.random(), 1 - p]) for _ in range(300)]
    got = {r["_host"]: r["_prior"] for r in language.host_priors(spark.createDataFrame(rows, "_host string, _p array<double>"), 2, 20.0).collect()}
    domain, suffix = (lambda h: ".".join(h.split(".")[-2:])), (lambda h: h.split(".")[-1])
    smooth = lambda own, up: [(sum(p[i] for p in own) + 20 * up[i]) / (len(own) + 20) for i in (0, 1)]
    every = smooth([p for _, p in rows], [0.5, 0.5])
    for h in {h for h, _ in rows}:
        up = smooth([p for g, p in rows if suffix(g) == suffix(h)], every)
        up = smooth([p for g, p in rows if domain(g) == domain(h)], up)
        assert got[h] == pytest.approx(smooth([p for g, p in rows if g == h], up))


def test_language_stage_with_clashing_columns(docs, empty):
    odd = docs.limit(50).withColumns({c: F.lit(1) for c in ("kept", "language", "confidence", "_text", "_row", "_host", "_c0", "a.b")})
    found = language.identified_documents(odd)
    assert found.columns == odd.columns and found.count() >= 45
    assert language.identified_documents(docs.withColumn("lang", F.lit(None).cast("string"))).count() == docs.count()
    assert language.identified_documents(empty).count() == 0


def test_evidence_moves_the_posterior(spark, docs):
    model = language.fit_text_model(docs)
    rows = spark.createDataFrame([(1, "de la", None, None), (2, "de la", "fr", None), (3, "de la", "es-MX", None), (4, "", "de", "http://a.de/x")], "i int, text string, d string, u string")
    got = {r["i"]: r for r in language.identify(rows, model, declared=F.col("d"), address=language.address_language(F.col("u"))).collect()}
    assert got[2]["language"] == "fr" and got[4]["language"] == "de" and not got[4]["kept"]
    page = spark.createDataFrame([("<!DOCTYPE html><HTML class=x lang='pt-BR'>", "https://x.com/fr/1"), ("<p lang=de>", "https://x.de:80/en")], "h string, u string")
    assert [tuple(r) for r in page.select(language.declared_language(F.col("h")), language.address_language(F.col("u"))).collect()] == [("pt-BR", "fr"), (None, "en")]


# ---------------------------------------------------------------- mixing


def brute_targets(sizes):
    w = [(3, 1, 2)[i % 3] for i in range(len(sizes))]
    left, target, capped = 1.5 * sum(sizes), [0.0] * len(sizes), set()
    while True:
        free = [i for i in range(len(sizes)) if i not in capped]
        total = sum(w[i] for i in free)
        rest = left - sum(2.0 * sizes[i] for i in capped)
        over = [i for i in free if rest * w[i] / total >= 2.0 * sizes[i]]
        if not over:
            for i in range(len(sizes)):
                target[i] = 2.0 * sizes[i] if i in capped else rest * w[i] / total
            return target
        capped |= set(over)


def test_mix_meets_targets(docs, odd, empty):
    for df in (docs, odd.drop("size").withColumn("mix", F.lit(0))):
        plan = mixing.mixing_plan(df).collect()
        texts = df.select("doc_id", "source", "text").collect()
        assert len(plan) == len(texts)
        sizes = collections.Counter()
        for r in texts:
            sizes[r["source"]] += len(WS.findall(r["text"] or ""))
        names = sorted(sizes, key=lambda s: (s is None, s or ""))
        want = dict(zip(names, brute_targets([sizes[s] for s in names]), strict=True))
        taken = collections.Counter()
        for r in plan:
            assert r["target"] == pytest.approx(want[r["source"]]) and 0 <= r["taken"] <= 2 * r["size"]
            taken[r["source"]] += r["taken"]
        assert all(taken[s] == int(want[s] + 1e-6) for s in names)
    assert mixing.mixing_plan(empty).count() == 0


def test_mixed_rows_are_the_planned_words(docs, empty):
    plan = {r["doc_id"]: r["taken"] for r in mixing.mixing_plan(docs).collect()}
    mixed = mixing.mixed_documents(docs)
    assert mixed.columns == docs.columns
    words = collections.Counter()
    whole = {r["doc_id"]: r["text"] for r in docs.collect()}
    for r in mixed.collect():
        words[r["doc_id"]] += len(WS.findall(r["text"]))
        assert whole[r["doc_id"]].startswith(r["text"]) and r["n_chars"] == len(r["text"])
    assert words == collections.Counter({k: v for k, v in plan.items() if v})
    assert mixing.mixed_documents(empty.drop("kept")).count() == 0


# ---------------------------------------------------------------- toxicity


def test_block_scan_equals_plain_forward_backward():
    rng = np.random.default_rng(3)
    sizes = [1, 5, 200, 64, 1, 130]
    e, move = rng.normal(0, 3, sum(sizes)), rng.normal(0, 1, (2, 2))
    begins = np.zeros(len(e), bool)
    begins[np.cumsum([0, *sizes[:-1]])] = True
    got, at = toxicity.marginals(e, begins, move), 0
    for n in sizes:
        em = np.exp(np.stack([np.zeros(n), e[at : at + n]], 1))
        t, a, b = np.exp(move), np.zeros((n, 2)), np.ones((n, 2))
        a[0] = em[0]
        for i in range(1, n):
            a[i] = (a[i - 1] @ t) * em[i]
            a[i] /= a[i].sum()
        for i in range(n - 2, -1, -1):
            b[i] = t @ (em[i + 1] * b[i + 1])
            b[i] /= b[i].sum()
        p = a * b
        assert np.allclose(got[at : at + n], p[:, 1] / p.sum(1), atol=1e-9)
        at += n


def test_toxicity_learns_and_keeps_clean_texts_clean(spark, odd, empty):
    random.seed(4)
    plain = ["".join(random.choices("abcdefghij", k=random.randint(2, 6))) for _ in range(300)]
    bad = ["zlorg", "quxxat", "vrimble"]
    def make(toxic):
        ws = random.choices(plain, k=random.randint(30, 200))
        for _ in range(3 if toxic else 0):
            ws.insert(random.randint(0, len(ws)), random.choice(bad))
        return " ".join(ws)
    y = [i % 4 == 0 for i in range(800)]
    texts = [make(t) for t in y]
    crf = toxicity.fit(texts[:500], [int(t) for t in y[:500]])
    df = spark.createDataFrame([(i, t) for i, t in enumerate(texts)], "doc_id long, text string")
    got = toxicity.score_toxicity(df, crf).collect()
    assert all((r["score"] >= 0.7) == y[r["doc_id"]] for r in got if r["doc_id"] >= 500)
    for r in got[:40]:
        assert sorted(texts[r["doc_id"]][s["start"] : s["end"]] for s in r["spans"]) == sorted(w for w in texts[r["doc_id"]].split() if w in bad)
    scores = {r["doc_id"]: r["score"] for r in toxicity.score_toxicity(odd, crf).collect()}
    assert scores[1] == scores[2] == scores[3] and all(0 <= s <= 1 for s in scores.values())
    assert toxicity.score_toxicity(empty, crf).count() == 0
    assert toxicity.fit(["a b"], [0]).scale[0] < 0


def test_labels_of_held_out_rows_change_nothing(spark, docs):
    labels = spark.read.parquet(f"{SF}/labels.parquet")
    held = F.pmod(F.crc32(F.col("doc_id").cast("string")), F.lit(3)) == 1
    flipped = labels.withColumn("toxic", F.when(held, 1 - F.col("toxic")).otherwise(F.col("toxic")))
    a, b = (toxicity.fit_toxicity(docs, x, ~held) for x in (labels, flipped))
    assert a.weights == b.weights and a.scale == b.scale


# ---------------------------------------------------------------- urls


def test_url_rules(spark):
    urls = [
        None, "", "no scheme", "http://EXAMPLE.com/en/1", "https://www.example.com/en/x?y#z", "http://a.www.example.com/en/", "http://notexample.com/en/", "http://x.net/fr/1", "http://x.net/fr", "http://net/es/",
        "http://x.org/es/", "http://m.ads-track.example.org/a", "http://spam-farm.example.org", "http://x.com", "http://com/", "http://x.org/casino/1", "http://x.org/Casinos", "ftp://b.net/es/?http://q.com/", "http://x.com/en/" + "a/" * 5000,
    ]
    pages = spark.createDataFrame([(i, u, 5) for i, u in enumerate(urls + urls)], "page_id long, url string, token int")
    got = url_filter.judge_urls(pages, [*url_filter.QUERY_RULES, *url_filter.GENERAL_RULES]).collect()
    assert len(got) == 2 * len(urls)
    for r in got:
        m = re.search(r"(?s)^.*?://([^/?#]*)([^?#]*)", r["url"] or "")
        host, path = (m[1].lower(), m[2]) if m else ("", "")
        fit = [x for x in url_filter.QUERY_RULES if re.search(x.pattern, host + path)]
        want = max(fit, key=lambda x: len(x.name), default=None)
        other = [x for x in url_filter.GENERAL_RULES if re.search(x.pattern, host + path)]
        assert (r["host"], r["path"], r["rule"]) == (host, path, want and want.name)
        assert r["verdict"] == (want.action if want else "block" if other else "allow")
    by = {r["url"]: r for r in got}
    assert by["http://x.com"]["rule"] is None and by["http://a.www.example.com/en/"]["verdict"] == "allow" and by["http://x.net/fr"]["rule"] is None
    assert url_filter.judge_urls(pages.where("page_id < 0"), url_filter.QUERY_RULES).count() == 0
    clashing = url_filter.judge_urls(pages.withColumns({c: F.lit("mine") for c in ("host", "path", "rule", "verdict", "page", "a.b")}), url_filter.QUERY_RULES)
    assert clashing.columns[-4:] == ["host", "path", "rule", "verdict"] and len(set(clashing.columns)) == len(clashing.columns)
    assert clashing.where("host = 'com' AND rule = 'com/' AND page = 'mine'").count() == 2


def test_rule_without_a_token_is_still_tried(spark):
    pages = spark.createDataFrame([(1, "http://a.b/xyz1"), (2, "http://a.b/q")], "page_id int, url string")
    rules = [url_filter.pattern_rule("x", "block", "yz[0-9]"), url_filter.host_rule("a.b", "", "allow")]
    assert {r["page_id"]: r["verdict"] for r in url_filter.judge_urls(pages, rules[:1]).collect()} == {1: "block", 2: "allow"}
    assert {r["rule"] for r in url_filter.judge_urls(pages, rules[1:]).collect()} == {"a.b"}


# ---------------------------------------------------------------- warc


def test_warc_round_trip(spark):
    dup, trap = "x" * 150, "\x1f\x8b\x08 not a record \x1f\x8b\x08" * 9
    rows = [(5, "http://a/1", dup), (3, "http://a/2\r\nX: y", dup), (9, None, dup), (1, "u", None), (2, "u", "short"), (4, "u", "short"), (None, "u", dup), (7, "ü", trap), (8, "u", "é" * 300_000), (11, "u", "WARC/1.1\r\n\r\n" * 5)]
    rows += [(100 + i, f"http://b/{i}", hashlib.sha256(str(i).encode()).hexdigest() * (i % 40)) for i in range(200)]
    pages = spark.createDataFrame(rows, "page_id long, url string, html string").repartition(3).withColumn("first", F.lit(1))
    files = warc.write_archives(pages, new_path(spark, "warc"))
    assert files.agg(F.sum("records")).first()[0] == len(rows)
    for size in (900, 5000, 8 << 20):
        got = warc.read_archives(files, range_bytes=size).collect()
        assert len(got) == len(rows)
        by = {r["page_id"]: r for r in got}
        for i, _, html in rows:
            raw = (html or "").encode()
            assert (by[i]["payload_bytes"], by[i]["payload_digest"]) == (len(raw), hashlib.sha256(raw).hexdigest())
            assert by[i]["record_type"] == ("revisit" if i in (5, 9, None) else "response")
            assert by[i]["refers_to"] == (3 if i in (5, 9, None) else None)
            assert by[i]["payload"] == (None if i in (5, 9, None) else raw)
    assert warc.read_archives(warc.write_archives(pages.where("page_id < 0"), new_path(spark, "warc"))).count() == 0


# ---------------------------------------------------------------- quality


def brute_repeats(words):
    seen = collections.defaultdict(list)
    for i in range(len(words) - 4):
        seen[tuple(words[i : i + 5])].append(i)
    return len({j for at in seen.values() if len(at) > 1 for i in at for j in range(i, i + 5)})


def test_base_measures_equal_brute_force(docs, odd, empty):
    for df in (docs, odd):
        texts = collections.defaultdict(list)
        for r in df.collect():
            texts[r["doc_id"]].append(r["text"] or "")
        rows = quality.line_quality(df).collect()
        assert len(rows) == df.count()
        for r in rows:
            t = texts[r["doc_id"]][0]
            words = WS.findall(t)
            lines = [x for x in t.split("\n") if WS.search(x)]
            rep = brute_repeats(words)
            want = (len(words), sum(map(len, words)), sum(c in "#*$%&|<>" for c in t), len(lines) - len(set(lines)), rep)
            assert (r["n_words"], r["word_chars"], r["n_symbols"], r["n_dup_lines"], r["n_repeat_words"]) == want
            assert r["base_failed"] == (len(words) < 10 or 100 * rep > 20 * len(words)) and not (r["base_failed"] and r["kept"])
    assert quality.line_quality(empty).count() == 0


def test_wide_vocabulary_windows():
    words = [f"w{i}".encode() for i in range(9000)]
    assert quality.repeated_words(words + words[:7]) == brute_repeats(words + words[:7]) == 14


def test_lines_go_and_documents_that_lose_too_much(spark):
    prose = "This is a clean line of ordinary prose that ends as it should."
    junk = "Home | About | Contact | Login | Terms"
    rows = [(1, f"{prose}\n{junk}\nAll rights reserved.\nAnother honest sentence stands here, and it is kept whole.", 0), (2, "\n".join([junk] * 9), 0), (3, prose, 0)]
    df = spark.createDataFrame(rows, "doc_id long, text string, n_chars int")
    got = {r["doc_id"]: r for r in quality.cleaned_documents(df).collect()}
    assert set(got) == {1, 3} and junk not in got[1]["text"] and "reserved" not in got[1]["text"] and got[1]["n_chars"] == len(got[1]["text"]) and got[3]["text"] == prose


# ---------------------------------------------------------------- joins


def sets_of(rows, k):
    low = lambda t: re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
    out = {}
    for i, t in rows:
        w = WS.findall(low(t))
        out[i] = frozenset(tuple(w[a : a + k]) for a in range(len(w) - k + 1)) if len(w) >= k else frozenset([tuple(w)] if w else [])
    return out


def brute_components(rows, k, percent):
    sets = sets_of(rows, k)
    head = {i: i for i in sets}

    def find(x):
        while head[x] != x:
            x = head[x]
        return x

    ids = [i for i in sets if sets[i]]
    for n, a in enumerate(ids):
        for b in ids[n + 1 :]:
            if 100 * len(sets[a] & sets[b]) >= percent * len(sets[a] | sets[b]):
                x, y = find(a), find(b)
                head[max(x, y)] = min(x, y)
    return {i: (len(sets[i]), find(i)) for i in sets}


def near_copies():
    random.seed(11)
    word = lambda: "".join(random.choices("abcdefgh", k=4))
    rows, n = [], 0
    for size in (4, 9, 10, 12, 20, 45, 150, 700):
        base = [word() for _ in range(size)]
        for edits in (0, 0, 0, 1, 1, 2, 3, 5, 8):
            w = list(base)
            for _ in range(edits):
                w[random.randrange(size)] = word()
            if edits == 2:
                w = w[: max(1, len(w) - 1)]
            rows.append((n, " ".join(w).replace("a", "A") if edits == 1 else " \n".join(w)))
            n += 1
    return rows + [(n, None), (n + 1, ""), (n + 2, "A b"), (n + 3, "a B"), (n + 4, "a b c")]


@pytest.mark.parametrize(("k", "percent"), [(3, 90), (5, 80)])
def test_components_equal_brute_force(spark, k, percent):
    rows = near_copies()
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("n_shingles", F.lit(1)).repartition(3)
    got = {r["doc_id"]: (r["n_shingles"], r["component_id"]) for r in shingle_join.similar_components(df, shingle_join.Similarity(k, percent)).collect()}
    assert got == brute_components(rows, k, percent)


def test_sketches_never_miss_a_link():
    rng = np.random.default_rng(5)
    for percent in (80, 90):
        like = shingle_join.Similarity(3, percent)
        for _ in range(300):
            n = int(rng.integers(3, 400))
            a = np.unique(rng.integers(0, 1 << 63, n, dtype=np.uint64))
            cut = int(rng.integers(0, max(1, len(a) // 8)))
            b = np.unique(np.concatenate([a[cut:], rng.integers(0, 1 << 63, int(rng.integers(0, max(1, n // 10))), dtype=np.uint64)]))
            assert shingle_join.sketch_distance(shingle_join.parity_bits(a), shingle_join.parity_bits(b)) <= len(np.setxor1d(a, b))
            if shingle_join._linked(a, b, like) and not np.array_equal(a, b):
                (x, need_a), (y, need_b) = shingle_join.block_keys(a, like), shingle_join.block_keys(b, like)
                assert len(set(x) & set(y)) >= max(need_a, need_b, 1)


def test_second_phase_joins_what_pivots_miss():
    rng, like = np.random.default_rng(6), shingle_join.Similarity(3, 90)
    base = np.unique(rng.integers(0, 1 << 63, 400, dtype=np.uint64))
    sets = {i: np.unique(np.concatenate([base[3 * i :], rng.integers(0, 1 << 63, 3 * i, dtype=np.uint64)])) for i in range(12)}
    links = shingle_join.connecting_links([(i, i, 0, s) for i, s in sets.items()], False, like)
    head = list(range(12))
    for a, b in links:
        x, y = head[a], head[b]
        head = [min(x, y) if h in (x, y) else h for h in head]
    want = list(range(12))
    for a in range(12):
        for b in range(a):
            if shingle_join._linked(sets[a], sets[b], like):
                x, y = want[a], want[b]
                want = [min(x, y) if h in (x, y) else h for h in want]
    assert head == want
    near = shingle_join.near_others([(i, i, 0, len(s), shingle_join.parity_bits(s)) for i, s in sets.items()], False, like)
    assert set(near) >= {i for i in range(12) if want.count(want[i]) > 1}


def test_join_edges(odd, empty):
    got = shingle_join.similar_components(odd).collect()
    assert len(got) == len(ODD) and {r["component_id"] for r in got if r["doc_id"] == 4} == {4}
    assert [r["component_id"] for r in got if r["doc_id"] is None] == [None]
    assert shingle_join.similar_components(empty).count() == 0
    kept = shingle_join.distinct_documents(odd)
    assert kept.columns == odd.columns and kept.where("doc_id = 4").count() == 1 and kept.where("doc_id IS NULL").count() == 1
    clashing = odd.withColumns({c: F.create_map(F.lit("a"), F.lit(1)) for c in ("kept_id", "again_id", "digest", "n", "a.b")})
    kept = shingle_join.distinct_documents(clashing)
    assert kept.columns == clashing.columns and kept.where("doc_id = 4").count() == 1 and shingle_join.distinct_documents(empty).count() == 0


def test_components_of_chains(spark):
    edges = [(i, i + 1) for i in range(0, 40)] + [(100, 90), (90, 95), (7, 7)]
    random.seed(2)
    random.shuffle(edges)
    got = {r["id"]: r["component"] for r in components.components(spark.createDataFrame(edges, "u long, v long")).collect()}
    assert got == {**{i: 0 for i in range(41)}, 100: 90, 90: 90, 95: 90}


# ---------------------------------------------------------------- packing


@pytest.mark.parametrize(("n", "top"), [(0, 10), (1, 1024), (40, 1024), (500, 700), (5000, 1024), (900, 90)])
def test_bins_hold_every_length_and_never_beat_the_bound(n, top):
    random.seed(n)
    counts = collections.Counter(random.randint(1, top) for _ in range(n))
    made = packing.bin_completion(dict(counts))
    held = collections.Counter()
    for m, lengths in made:
        assert sum(lengths) <= 1024 and m > 0
        for x in lengths:
            held[x] += m
    assert held == counts
    first = sum(m for m, _ in packing.best_fit_decreasing(dict(counts), 1024))
    assert -(-sum(counts.elements()) // 1024) <= sum(m for m, _ in made) <= first


def test_bin_completion_is_optimal_on_small_cases():
    for seed in range(12):
        random.seed(seed)
        items = [random.randint(2, 9) for _ in range(8)]

        def best(left, rooms):
            if not left:
                return len(rooms)
            x, *rest = left
            out = best(rest, [*rooms, 12 - x]) if len(rooms) < 6 else 99
            for i, r in enumerate(rooms):
                if r >= x:
                    out = min(out, best(rest, [*rooms[:i], r - x, *rooms[i + 1 :]]))
            return out

        assert sum(m for m, _ in packing.bin_completion(dict(collections.Counter(items)), 12)) == best(sorted(items, reverse=True), [])


def test_bin_completion_fills_with_many_short_pieces():
    for counts, size, want in (({300: 400, 212: 200, 106: 400}, 1024, 200), ({300: 402, 212: 201, 106: 402}, 1024, 201), ({7: 6, 5: 6, 3: 12, 2: 6}, 20, 6)):
        bins = packing.bin_completion(counts, size)
        assert sum(n for n, _ in bins) == want and all(sum(held) <= size for _, held in bins)
        held = collections.Counter()
        for n, pieces in bins:
            held.update({x: n * k for x, k in collections.Counter(pieces).items()})
        assert held == counts


def test_packed_pieces(spark, docs, odd, empty):
    bpe = tokens.byte_bpe()
    for df in (docs, odd):
        rows = packing.pack_documents(df).collect()
        by, seqs = collections.defaultdict(list), collections.defaultdict(list)
        for r in rows:
            by[r["doc_id"]].append(r)
            seqs[r["sequence_id"]].append((r["offset"], r["length"]))
        for t in df.collect():
            ids = bpe.encode(t["text"] or "") + (2).to_bytes(4, "little")
            own = sorted(by[t["doc_id"]], key=lambda r: r["start"])
            for s, n in packing.pieces_of(len(ids) // 4, 1024):
                assert any(r["start"] == s and r["length"] == n and r["ids_crc32"] == zlib.crc32(ids[4 * s : 4 * (s + n)]) for r in own)
        for held in seqs.values():
            at = 0
            for o, n in sorted(held):
                assert o == at
                at += n
            assert at <= 1024
        total = sum(r["length"] for r in rows)
        assert len(seqs) <= -(-total // 1024) + 3
    assert packing.pack_documents(empty).count() == 0
    layout = packing.pack_documents(docs)
    made = packing.token_sequences(docs, layout).collect()
    assert sum(len(r["ids"]) for r in made) == layout.agg(F.sum("length")).first()[0] and all(len(r["ids"]) == sum(r["lengths"]) for r in made)


def test_ids_equal_the_tokenizers_file(docs):
    import public_tokenizers
    from tokenizers import Tokenizer

    whole, bpe = Tokenizer.from_file(public_tokenizers.path("byte_bpe_50k.json")), tokens.byte_bpe()
    odd = ["", " ", "  a", "a  b", "a \n b", "\n\n x", " lead", "trail ", "tab\tx  y", "don't we'll", "日本語 テキスト", "a<|endoftext|>b", "x" * 500, "1234 5 67", "   z", "é \r\n z"]
    for t in [*odd, *(r["text"] for r in docs.limit(60).collect())]:
        assert list(np.frombuffer(bpe.encode(t), "<u4")) == whole.encode(t, add_special_tokens=False).ids, t[:40]


def test_sets_with_empty_blocks_need_one_shared_key():
    """Of e + 1 blocks shared with a partner that has e empty ones and keeps them back, one is sure to meet."""
    like, rng, seen = shingle_join.Similarity(), np.random.default_rng(3), 0
    low = shingle_join.bands(like.percent)
    for n in range(2400, 3300, 50):  # some enter the next, larger band with many empty blocks
        s = np.sort(rng.integers(0, 1 << 63, n).astype(np.uint64))
        own = int(np.searchsorted(low, n, side="right")) - 1
        keys, need = shingle_join.block_keys(s, like)
        for band in range(own, own + 1 + int(n * 100 // like.percent >= low[own + 1])):
            t = like.differences(2 * int(low[band + 1] - 1))
            blocks = shingle_join.block_count(t, int(low[band])) if t else 0
            every = {int(k) for k in shingle_join._mix(shingle_join._mix(np.arange(blocks).astype(np.uint64) + np.uint64(band << 40))).view(np.int64)}  # keys of empty blocks
            if len(every & set(keys.tolist())):
                seen += 1
                assert need == 1
    assert seen


# ---------------------------------------------------------------- webp


def test_webp_round_trips():
    rng = np.random.default_rng(1)
    for rows in (1, 2, 7):
        for payload in (rng.integers(0, 256, 192 * rows, dtype=np.uint8).tobytes(), b"text " * 40 * rows + b" " * 192, b"a" * 192 * rows):
            payload = webp.padded(payload)
            for level in (0, 1):
                assert webp.from_media(webp.to_media(payload, level)).tobytes() == payload
    long = webp.padded(b"long text " * 400_000)
    media = webp.to_media(long)
    assert len(webp.decode(media)) == 2 and webp.from_media(media).tobytes() == long


def stream(width, height):
    b = webp.Bits()
    b.write(0x2F, 8), b.write(width - 1, 14), b.write(height - 1, 14), b.write(0, 4)
    return b


def one(b, *symbols):
    """Simple prefix codes of one or two symbols."""
    for s in symbols:
        s = s if isinstance(s, tuple) else (s,)
        b.write(1, 1), b.write(len(s) - 1, 1), b.write(1, 1), b.write(s[0], 8)
        if len(s) == 2:
            b.write(s[1], 8)


def sub_image(b, r, g, bl):
    b.write(0, 1)
    one(b, g, r, bl, 255, 0)


def test_webp_back_references_and_cache():
    b = stream(4, 2)
    b.write(0, 1), b.write(0, 1), b.write(0, 1)
    # green: literal 9 or a copy of prefix 259 (lengths 4), then distance codes
    lengths = [0] * 280
    lengths[9] = lengths[256 + 3] = 1
    webp._write_code(b, lengths)
    one(b, 5, 6, 255, 1)
    for bit in (0, 1, 1):
        b.write(bit, 1)
    px = webp.decode(webp._riff(b.bytes()))[0]
    assert px.shape == (2, 4, 4) and (px == [5, 9, 6, 255]).all()
    b = stream(3, 1)
    b.write(0, 1), b.write(1, 1), b.write(1, 4), b.write(0, 1)
    colour = 255 << 24 | 5 << 16 | 9 << 8 | 6
    slot = (webp.CACHE_FACTOR * colour & 0xFFFFFFFF) >> 31
    lengths = [0] * 282
    lengths[9] = lengths[280 + slot] = 1
    webp._write_code(b, lengths)
    one(b, 5, 6, 255, 0)
    for bit in (0, 1, 1):
        b.write(bit, 1)
    assert (webp.decode(webp._riff(b.bytes()))[0] == [5, 9, 6, 255]).all()


def test_webp_steps_and_headers():
    rng = np.random.default_rng(3)
    for n, start in ((1, 0), (7, 3), (500, 2), (3000, 0)):
        ends = np.arange(n) + rng.integers(1, 30, n)
        want, p = [], start
        while p < n:
            want.append(p)
            p = int(ends[p])
        assert webp._followed(ends, start).tolist() == want
    for counts in ([5, 1, 1] + [0] * 253, rng.integers(0, 9, 256), rng.integers(0, 2, 256) * 2 ** rng.integers(0, 16, 256)):
        bits, sizes = webp.Bits(), webp._sizes(np.asarray(counts))
        webp._write_code(bits, sizes)
        end, back = bits.n, webp.Bits(bits.bytes() + bytes(4))
        assert (webp._read_code(back, 256).sizes == sizes).all() and back.at == end


def test_webp_transforms():
    # left predictor over constant residuals: a running sum along each row
    b = stream(5, 2)
    b.write(1, 1), b.write(0, 2), b.write(0, 3)
    sub_image(b, 0, 1, 0)
    b.write(0, 1), b.write(0, 1), b.write(0, 1)
    one(b, 3, 2, 1, 0, 0)
    px = webp.decode(webp._riff(b.bytes()))[0]
    assert px[0, :, 0].tolist() == [2, 4, 6, 8, 10] and px[0, :, 1].tolist() == [3, 6, 9, 12, 15] and px[1, 0].tolist() == [4, 6, 2, 255] and (px[..., 3] == 255).all()
    # cross-colour: red += (green_to_red * green) >> 5, blue += by green and by the new red
    b = stream(2, 1)
    b.write(1, 1), b.write(1, 2), b.write(0, 3)
    sub_image(b, 16, 64, 32)
    b.write(0, 1), b.write(0, 1), b.write(0, 1)
    one(b, 10, 20, 30, 255, 0)
    assert webp.decode(webp._riff(b.bytes()))[0][0, 0].tolist() == [30, 10, 30 + 20 + 15, 255]
    # palette of two colours, eight indices a pixel
    b = stream(8, 1)
    b.write(1, 1), b.write(3, 2), b.write(1, 8)
    b.write(0, 1)
    one(b, (10, 20), 1, 2, (0, 255), 0)
    b.write(0, 1), b.write(1, 1), b.write(1, 1), b.write(0, 1)
    b.write(0, 1), b.write(0, 1), b.write(0, 1)
    one(b, 0b10110010, 0, 0, 255, 0)
    px = webp.decode(webp._riff(b.bytes()))[0]
    assert px[0, :, 1].tolist() == [30 if 0b10110010 >> i & 1 else 10 for i in range(8)]


def test_webp_writer_compresses(docs, monkeypatch):
    seen = collections.Counter()
    for name in ("_undo_palette", "_undo_predictor"):
        monkeypatch.setattr(webp, name, lambda *a, f=getattr(webp, name), k=name: (seen.update([k]), f(*a))[1])
    rng = np.random.default_rng(2)
    slope = ((np.add.outer(np.arange(90), 3 * np.arange(64))[..., None] * [1, 2, 5]) + rng.integers(0, 3, (90, 64, 3))).astype(np.uint8)
    words = [bytes(rng.integers(97, 123, rng.integers(2, 9), dtype=np.uint8)) for _ in range(300)]
    prose = webp.padded(b" ".join(words[int(i)] for i in rng.integers(0, 300, 3000)))
    for px, kind in ((slope, "_undo_predictor"), (slope.swapaxes(0, 1), "_undo_predictor"), (np.frombuffer(webp.padded(b"few colours " * 50), np.uint8).reshape(-1, 64, 3), "_undo_palette"), (np.frombuffer(prose, np.uint8).reshape(-1, 64, 3), None)):
        before = seen[kind]
        media = webp.encode(px)
        assert len(media) < 0.8 * px.size and (webp.decode(media)[0][..., :3] == px).all()
        assert kind is None or seen[kind] == before + 1
    noise = rng.integers(0, 256, (webp.BLOCK // 800, 64, 3), dtype=np.uint8)  # several blocks of bits
    assert (webp.decode(webp.encode(noise))[0][..., :3] == noise).all()
    sizes = webp.media_digests(docs).agg(F.sum("media_bytes"), F.sum("payload_bytes")).first()
    assert sizes[0] < 0.7 * sizes[1]


def test_media_digests(docs, odd, empty):
    for df in (docs, odd):
        texts = [r["text"] or "" for r in df.collect()]
        got = webp.media_digests(df).collect()
        want = sorted((len(t.encode()), hashlib.sha256(webp.padded(t.encode())).hexdigest(), zlib.crc32(webp.padded(t.encode())[-16:])) for t in texts)
        assert sorted((r["n_bytes"], r["payload_sha256"], r["tail_crc32"]) for r in got) == want
        assert all(r["payload_bytes"] % 192 == 0 and r["payload_bytes"] for r in got)
    assert webp.media_digests(empty).count() == 0
    kinds = webp.media_digests(docs).agg(*[F.sum(f"n_{k}") for k in ("literals", "copies", "cache_hits", "palettes")]).first()
    assert all(kinds)
    back = webp.pixel_arrays(webp.media_column(odd)).where("doc_id = 4").first()
    assert bytes(back["rgba"][:3]) == b"one" and (back["width"], back["height"]) == (64, 1)


# ---------------------------------------------------------------- pipeline


def test_pipeline_stages(spark, docs):
    import corpus_pipeline as p

    now, columns, before = docs, docs.columns, docs.count()
    for name, step in p.STAGES[:-1]:
        now = step(spark, now, SF)
        assert now.columns == columns, name
        now = spark.createDataFrame(now.collect(), docs.schema)
        if name != "source_mixing":
            assert now.count() <= before
            before = now.count()
    ids = {r["doc_id"] for r in now.collect()}
    last = p.STAGES[-1][1](spark, now, SF)
    assert {r["doc_id"] for r in last.collect()} == ids
    assert [n for n, _ in p.STAGES] == ["language_id", "quality_rules", "near_copies", "source_mixing", "best_fit_packing"]


def test_pipeline_of_odd_and_empty_documents(spark, docs, odd, empty, tmp_path):
    import corpus_pipeline as p

    plain = docs.limit(40).withColumns({"size": F.lit("mine"), "kept": F.lit(1), "rep": F.lit(2), "tokens": F.lit(3)})
    for k, now in enumerate((odd.unionByName(plain), empty)):
        for name, step in p.STAGES:
            step(spark, now, SF).write.parquet(f"{tmp_path}/{k}-{name}")
            now = spark.read.parquet(f"{tmp_path}/{k}-{name}")
            assert name == "best_fit_packing" or now.columns == odd.columns
        assert now.count() == 0 if k else now.count() > 0


def test_pipeline_runs_whole(spark, docs):
    import corpus_pipeline as p

    whole = p.run(spark, SF).collect()
    now = docs
    for _, step in p.STAGES:
        now = spark.createDataFrame((made := step(spark, now, SF)).collect(), made.schema)
    place = lambda rows: sorted((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in rows)
    assert whole and place(whole) == place(now.collect())


def test_near_copy_stage_keeps_one_of_each_component(spark):
    import corpus_pipeline as p

    rows = near_copies()
    df = spark.createDataFrame([(i, t, "en", "s", len(t or "")) for i, t in rows], DOC)
    comp = brute_components(rows, 5, 80)
    want = sorted(i for i, (n, c) in comp.items() if n == 0 or c == i)
    assert sorted(r["doc_id"] for r in p.drop_near_copies(spark, df, SF).collect()) == want


def test_registered_queries():
    assert {k.split("_")[0] for k in registry.QUERIES} == {f"op{i}" for i in range(1, 11)}
    assert set(registry.SQL) <= set(registry.QUERIES)
    assert text.WORD == r"[^\x20\x09-\x0D]+"
