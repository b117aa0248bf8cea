"""The training-data operators against brute force, the tokenizer library, held-out accuracy and edge cases."""

import hashlib
import math
import re
import time
import zlib
from collections import Counter

import numpy as np
import public_tokenizers
import pytest
import regex
import tiktoken
import xxhash
from pyspark.sql import functions as F

from vecrag.llm import ball, bpe, chat, cnn, graph, html, licenses, mixing, ppm, registry, simhash, spots
from vecrag.llm.common import held_out, table

SF = "/root/testdata/sf0.001"
RANKS = public_tokenizers.path("byte_bpe_50k.tiktoken")
DOC = "doc_id long, text string, lang string, source string, n_chars long"
ODD = [(1, None, None, None, None), (2, "", "en", "a", 0), (3, "The same text of the same words.", "en", "a", 32), (4, "The same text of the same words.", "en", None, 32), (4, "The same text of the same words.", "en", "b", 32), (None, "no id", "fr", "b", 5), (6, "word " * 20000, "en", "a", 100000), (7, "日本語 \U0001f600 éè", "xx", "c", 9), (8, "!!! ... 123", "en", "c", 11)]


@pytest.fixture(scope="module")
def docs(spark):
    return table(spark, SF, "documents")


@pytest.fixture(scope="module")
def odd(spark):
    return spark.createDataFrame(ODD, DOC).withColumn("score", F.lit("clash")).withColumn("fp", F.lit(1)).withColumns({c: F.lit("mine") for c in ("_s", "gone", "turn", "key", "c0", "node", "comp", "s", "t", "same")})


def empty(spark):
    return spark.createDataFrame([], DOC)


# -- 1: main text ----------------------------------------------------------------------------------------------------------
def test_op1_equals_the_article_of_the_given_pages(spark):
    import html as entities

    def article(page):
        body = re.search(r"<article>(.*?)(?:</article>|$)", page, re.S)[1]
        parts = [" ".join(entities.unescape(re.sub("<[^>]*>", "", x)).split()) for x in re.split(r"</?(?:h1|p)>", body)]
        return "\n".join(x for x in parts if x)

    pages = {r["page_id"]: r["html"] for r in table(spark, SF, "pages").collect()}
    rows = registry.op1_html(spark, SF).collect()
    assert len(rows) == len(pages)
    for r in rows:
        assert r["text"] == article(pages[r["page_id"]]) and r["n_chars"] == len(r["text"])


LONG = "The bridge over the river was opened by the mayor on a cold morning in May. "


@pytest.mark.parametrize(
    ("page", "text"),
    [
        (None, ""), ("", ""), ("<p>unclosed", "unclosed"), ("<article><p>a &lt;b&gt; &eacute;&#233; &amp</p><p> x \n\t y </p></article>", "a <b> éé &\nx y"),
        ("<article><p>one<script>if (a < b) { '</p>' }</script> two</p></article>", "one two"),
        ("<article><p>k</p><aside>no</aside><form>no</form><div class='comments'><p>no no</p></div><div class='cookie-banner'>no</div></article><footer>no</footer>", "k"),
        ("<nav>a b c</nav><header>h</header><main><h1>t</h1><p>x<!-- </main> --></p></main>", "t\nx"),
        ("<article><p>x" + "<b>" * 3000 + "y</article>", "xy"), ("<article><p title='a>b'>q</p><p title=\"x>y\">r</p></article>", "q\nr"), ("<article><p>a<p>b<ul><li>c<li>d</ul></article>", "a\nb\nc\nd"),
    ],
)
def test_op1_cases(page, text):
    assert html.main_text(page, html.train()) == text


@pytest.mark.parametrize(
    ("page", "text"),
    [
        ("<html><head><title>x</title><p>Some text", "Some text"), ("<head><title>x</title>Some text</head><p>more", "Some text\nmore"),
        (f"<div id=main><p>Intro</p></div><p>{LONG * 2}</p><p>{LONG * 3}</p>", f"Intro\n{(LONG * 2).strip()}\n{(LONG * 3).strip()}"),
        (f"<div class='tags-of-rain'><p>{LONG * 2}</p></div><div class='newsletter-story'><p>{LONG}</p></div>", f"{(LONG * 2).strip()}\n{LONG.strip()}"),
        (f"<div class='ad-slot-top'>{LONG}</div><article><p>{LONG}</p></article><div class='site-footer'>{LONG}</div>", LONG.strip()),
        (f"<div><a href=/a>home</a> <a href=/b>news</a></div><div>Log in</div><div><a href=/a>home</a> <a href=/b>news</a></div><p>{LONG * 2}</p><p>No.</p><p>{LONG * 2}</p>"
         "<div><a href=/a>home of all the things in it</a></div><div>Follow us</div><div><a href=/a>home</a> <a href=/b>news</a></div>", f"{(LONG * 2).strip()}\nNo.\n{(LONG * 2).strip()}"),
    ],
)
def test_op1_misleading_structure(page, text):
    assert html.main_text(page, html.train()) == text


def test_op1_tree_uses_words_links_and_neighbours():
    used = {html.FEATURES[f] for f, *_ in html.train() if f >= 0}
    assert {"words", "link_density"} <= used and used & {"words_before", "link_density_before", "words_after", "link_density_after"}


def test_op1_without_structure():
    tree = html.train()
    page = f"<div><a href=/a>home</a> <a href=/b>news</a></div><p>{LONG * 2}</p><p>{LONG}</p><div><a href=/c>terms</a> <a href=/d>privacy</a></div>"
    assert html.main_text(page, tree) == f"{(LONG * 2).strip()}\n{LONG.strip()}"


def test_op1_tree_learns():
    x = np.array([[0.0], [1], [2], [3]])
    old, html.ORDER = html.ORDER, [0]
    try:
        tree = html.grow(x, np.array([0.0, 0, 1, 1]))
    finally:
        html.ORDER = old
    assert html.predict(tree, np.array([[1.4], [1.6]])).tolist() == [0.0, 1.0]


def test_op1_rows_are_kept(spark):
    df = spark.createDataFrame([(1, "u", "<p>x</p>", "t"), (1, "u", "<p>x</p>", "t"), (None, None, None, None)], "page_id long, url string, html string, text string")
    assert sorted((r["page_id"] or 0, r["text"], r["n_chars"]) for r in html.extract(df).collect()) == [(0, "", 0), (1, "x", 1), (1, "x", 1)]
    assert html.extract(df.limit(0)).count() == 0


# -- 2: language -------------------------------------------------------------------------------------------------------------
def test_op2_code_lengths_equal_brute_force():
    tree = ppm.ContextTree.fit(["abracadabra", "the cat sat", "été"])

    def brute(text):
        body, total = b"\n\n\n" + text.lower().encode(), 0.0
        counts = [Counter() for _ in range(4)]
        for t in ("abracadabra", "the cat sat", "été"):
            raw = b"\n\n\n" + t.encode()
            for i in range(3, len(raw)):
                for o in range(4):
                    counts[o][raw[i - o : i + 1]] += 1
        for i in range(3, len(body)):
            for o in (3, 2, 1, 0):
                after = {g: n for g, n in counts[o].items() if g[:-1] == body[i - o : i]}
                if not after:
                    continue
                weight = sum(after.values()) + len(after)
                if body[i - o : i + 1] in after:
                    total -= math.log2(after[body[i - o : i + 1]] / weight)
                    break
                total -= math.log2(len(after) / weight)
            else:
                total += 8
        return total

    texts = ["abra", "The hat!", "", "zzé", "x"]
    assert ppm.code_lengths([tree], texts)[:, 0] == pytest.approx([brute(t) for t in texts])


def test_op2_held_out_accuracy(spark):
    truth = {r["doc_id"]: r["lang"] for r in table(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "lang").collect()}
    rows = registry.op2_language(spark, "/root/testdata/sf0.01").where("held_out").collect()
    assert {r["held_out"] for r in rows} == {True} and all(zlib.crc32(str(r["doc_id"]).encode()) % 4 == 2 for r in rows)
    assert np.mean([r["lang_pred"] == truth[r["doc_id"]] for r in rows]) > 0.97


def test_op2_edges(spark, docs, odd):
    model = ppm.train(docs)
    rows = ppm.identify(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r["score"] <= 1 for r in rows)
    assert {r["doc_id"]: r["lang_pred"] for r in rows if r["doc_id"] in (1, 2, 8)} == {1: "und", 2: "und", 8: "und"}
    assert ppm.keep_identified(odd, model).columns == odd.columns
    assert ppm.identify(empty(spark), model).count() == 0
    nothing = ppm.train(empty(spark))
    assert {r["lang_pred"] for r in ppm.identify(odd, nothing).collect()} == {"und"}


def test_op2_learns_from_long_texts_only(spark):
    en, fr = "the house and the river were quiet in the evening ", "la maison et la riviere sont calmes dans le soir "
    rows = [(k, (fr if k % 2 else en) * (600 if k % 2 else 3), "fr" if k % 2 else "en") for k in range(60)]
    df = spark.createDataFrame(rows, "doc_id long, text string, lang string")
    model = ppm.train(df)
    assert model.languages == ["en", "fr"]
    assert {(r["lang_pred"]) for r in ppm.identify(df.where("lang = 'fr'"), model).collect()} == {"fr"}


def test_op2_unusual_codes_are_rejected(spark, docs):
    model = ppm.train(docs)
    rng = np.random.default_rng(0)
    junk = "".join(rng.choice(list("qxzjkvwpyg7"), 400))
    df = spark.createDataFrame([(1, junk, None), (2, docs.where("lang = 'en' and n_chars > 300").first()["text"], None)], "doc_id long, text string, lang string")
    assert [r["doc_id"] for r in ppm.keep_identified(df, model).collect()] == [2]


def test_long_texts_are_sampled_by_windows(spark):
    from vecrag.llm.common import sampled_text

    text = "".join(chr(97 + k % 26) + str(k) for k in range(3000))
    df = spark.createDataFrame([(1, text), (2, "short"), (3, None)], "id long, t string")
    got = {r["id"]: r["s"] for r in df.select("id", sampled_text(F.col("t"), F.col("id"), 1000, 10, 42).alias("s")).collect()}
    parts = got[1].split("\n")
    assert got[2] == "short" and got[3] is None and len(parts) == 10 and all(len(p) == 100 and p in text for p in parts)
    at = [text.index(p) for p in parts]
    assert at == sorted(at) and at[0] < len(text) // 10 and at[-1] >= len(text) * 9 // 10 - 10


def test_held_out_matches_zlib(spark):
    rows = spark.range(500).select("id", held_out("id").alias("h")).collect()
    assert all(r["h"] == (zlib.crc32(str(r["id"]).encode()) % 4 == 2) for r in rows)


# -- 3: fingerprints -----------------------------------------------------------------------------------------------------------
def test_op3_equals_brute_force(spark, docs):
    given = sorted((r["doc_id"], r["text"] or "") for r in docs.select("doc_id", "text").collect())
    rows = {r["doc_id"]: r for r in registry.op3_spotsigs(spark, SF).collect()}
    assert len(rows) == len(given)
    sets = [set(spots.signature_set(t).tolist()) for _, t in given]
    like = lambda a, b: 1.0 if not a and not b else len(a & b) / len(a | b)
    for k, (i, t) in enumerate(given):
        nxt = given[(k + 1) % len(given)][1]
        gone = len(t) // 4
        edited = t[: len(t) - gone] + nxt[:gone]
        r = rows[i]
        assert r["n_chars"] == len(t) and r["edited_sha256"] == hashlib.sha256(edited.encode()).hexdigest()
        assert r["near_edited"] == pytest.approx(like(sets[k], set(spots.signature_set(edited).tolist())))
        assert r["near_next"] == pytest.approx(like(sets[k], sets[(k + 1) % len(given)]))
        assert r["fingerprint"] == "".join(f"{x:08x}" for x in sorted(sets[k]))


def test_op3_signatures():
    h = lambda s: xxhash.xxh32_intdigest(s)
    assert spots.signature_set("The quick fox of brown").tolist() == sorted([h("the:quick fox")])
    assert spots.signature_set("alpha beta").tolist() == [h("alpha beta")]
    assert spots.signature_set("the of").tolist() == sorted({h("the"), h("of")})
    assert spots.signature_set("!!").tolist() == [h("!!")] and spots.signature_set(None).size == 0


def test_op3_edges(spark, odd):
    rows = spots.fingerprint_edits(odd).collect()
    assert sorted(str(r["doc_id"]) for r in rows) == sorted(str(x[0]) for x in ODD)
    assert len({r["fingerprint"] for r in rows if r["doc_id"] in (3, 4)}) == 1
    assert spots.fingerprint_edits(empty(spark)).count() == 0
    one = spots.fingerprint_edits(spark.createDataFrame([ODD[2]], DOC)).collect()
    assert len(one) == 1 and one[0]["near_next"] == 1.0
    far = spark.createDataFrame([(1 << 60, "the last one of all"), (-(1 << 60), "the first one of all"), (5, "abcd")], "doc_id long, text string")
    got = {r["doc_id"]: r["edited_sha256"] for r in spots.fingerprint_edits(far).collect()}
    assert got[5] == hashlib.sha256(b"abct").hexdigest()


def test_op3_matching_equals_brute_force(spark, docs):
    given = [(r["doc_id"], set(spots.signature_set(r["text"]).tolist())) for r in docs.collect()]
    base = " ".join(f"the alpha{i} beta{i}" for i in range(40))
    extra = [(900, base), (901, base + " the tail end"), (902, base), (903, "the " + base)]
    given += [(i, set(spots.signature_set(t).tolist())) for i, t in extra]
    label = {i: i for i, _ in given}
    for _ in range(5):
        for i, a in given:
            for j, b in given:
                if i != j and (len(a & b) >= 0.8 * len(a | b) - 1e-9):
                    label[i] = min(label[i], label[j])
    both = docs.select("doc_id", "text").unionByName(spark.createDataFrame(extra, "doc_id long, text string"))
    got = {r["doc_id"]: r["class_id"] for r in spots.near_duplicates(both).collect()}
    assert got == label and len({got[i] for i in (900, 901, 902, 903)}) == 1


# -- 4: SimHash ----------------------------------------------------------------------------------------------------------------
def brute_fingerprint(text):
    lowered = "".join(chr(ord(c) + 32) if "A" <= c <= "Z" else c for c in text or "")
    words = re.findall(r"[^\x20\x09-\x0D]+", lowered)
    shingles = [" ".join(words[i : i + 4]) for i in range(max(1, len(words) - 3))] if words else []
    ones = [0] * 64
    for s in shingles:
        h = xxhash.xxh64_intdigest(s.encode(), seed=42)
        for b in range(64):
            ones[b] += h >> b & 1
    return sum(1 << b for b in range(64) if 2 * ones[b] > len(shingles))


def brute_components(prints):
    label = {i: i for i, _ in prints}
    while True:
        new = {i: min(label[j] for j, g in prints if (f ^ g).bit_count() <= 4) for i, f in prints}
        if new == label:
            return label
        label = new


def test_op4_equals_brute_force(spark, docs):
    prints = [(r["doc_id"], brute_fingerprint(r["text"])) for r in docs.collect()]
    want = brute_components(prints)
    rows = registry.op4_simhash(spark, SF).collect()
    assert len(rows) == len(prints)
    assert {r["doc_id"]: r["fingerprint"] for r in rows} == {i: f"{f:016x}" for i, f in prints}
    assert {r["doc_id"]: r["component_id"] for r in rows} == want


@pytest.mark.parametrize("shard", [20_000, 7])
def test_op4_chains_and_hot_shards(spark, monkeypatch, shard):
    monkeypatch.setattr(simhash, "SHARD", shard)
    rng = np.random.default_rng(5)
    base = [int(x) for x in rng.integers(0, 1 << 62, 4)]
    prints = {}
    for b in base:
        f = b
        for _ in range(12):  # a chain: neighbours within 3 bits, ends far apart
            for k in rng.choice(64, 3, replace=False):
                f ^= 1 << int(k)
            prints[len(prints)] = f
    prints = [(i, f) for i, f in prints.items()]
    signed = [(f - (1 << 64) if f >> 63 else f, i) for i, f in prints]
    reps = spark.createDataFrame(signed, "fp long, rep long")
    found = {r["node"]: r["component"] for r in graph.components(simhash.near_links(reps)).collect()}
    want = brute_components(prints)
    assert {i: found.get(i, i) for i, _ in prints} == want


@pytest.mark.parametrize("n", [10, 10**6, 10**9, 10**13])
def test_op4_masks_lose_no_pair(n):
    rng = np.random.default_rng(n % 97)
    masks = simhash.masks(n)
    for _ in range(300):
        x = int(rng.integers(0, 1 << 63))
        y = x
        for k in rng.choice(64, 4, replace=False):
            y ^= 1 << int(k)
        assert any((x & m) == (y & m) for m in masks)


def test_op4_edges(spark, odd):
    rows = simhash.cluster(odd).collect()
    assert len(rows) == len(ODD)
    by = {r["doc_id"]: r for r in rows}
    assert by[1]["fingerprint"] == by[2]["fingerprint"] == "0" * 16 and by[2]["component_id"] == 1
    assert by[4]["component_id"] == 3 and by[6]["component_id"] == 6
    kept = simhash.keep_one(odd)
    assert kept.columns == odd.columns
    assert sorted(str(r["doc_id"]) for r in kept.collect()) == sorted(map(str, [1, 3, None, 6, 7, 8]))
    assert simhash.cluster(empty(spark)).count() == 0 and simhash.keep_one(empty(spark)).count() == 0


def test_components_of_a_path_and_a_star(spark):
    path = [(i, i + 1) for i in range(100, 160)]
    star = [(500, 500 + k) for k in range(1, 40)]
    got = {r["node"]: r["component"] for r in graph.components(spark.createDataFrame(path + star + [(7, 7), (None, 3)], "a long, b long")).collect()}
    assert {got[i] for i in range(100, 161)} == {100} and {got[i] for i in range(500, 540)} == {500} and 7 not in got and 3 not in got


def test_components_of_few_links_take_few_stages(spark):
    rng = np.random.default_rng(3)
    pairs = [(int(a), int(b)) for a, b in rng.integers(0, 300, (150, 2)) - 5] + [(10_000 + k, 10_001 + k) for k in range(40)]
    links = spark.createDataFrame([*pairs, (4, None)], "a long, b long").repartition(6)
    sc = spark.sparkContext
    sc.setJobGroup("few links", "")
    one = {r["node"]: r["component"] for r in graph.components(links).collect()}
    sc.setJobGroup("rounds", "")
    assert one == {r["node"]: r["component"] for r in graph.components(links, small=0).collect()}
    sc.setJobGroup("", "")
    assert one[10_040] == 10_000 and min(one.values()) < 0
    tracker = sc.statusTracker()
    stages = {name: sum(len(tracker.getJobInfo(j).stageIds) for j in tracker.getJobIdsForGroup(name)) for name in ("few links", "rounds")}
    assert stages["few links"] <= 10 < stages["rounds"]


# -- 5: mixing -------------------------------------------------------------------------------------------------------------------
def test_op5_exponent():
    tokens = np.array([1000.0, 100, 10])
    x = mixing.solve_exponent(tokens, tokens.sum(), 0.9, None)
    assert mixing.entropy(mixing.weights(tokens, x)) == pytest.approx(0.9 * math.log(3), abs=1e-9)
    y = mixing.solve_exponent(tokens, tokens.sum(), None, 2.0)
    assert (mixing.weights(tokens, y) * tokens.sum() / tokens).max() == pytest.approx(2.0, abs=1e-6)
    assert mixing.solve_exponent(tokens, tokens.sum(), 0.9, 2.0) == pytest.approx(max(x, y))
    assert mixing.solve_exponent(np.array([5.0]), 5, 0.9, 2) == 1.0 and mixing.solve_exponent(np.zeros(0), 0, 0.9, 2) == 1.0
    with pytest.raises(ValueError):
        mixing.solve_exponent(tokens, 5 * tokens.sum(), None, 2.0)


def test_op5_budgets_equal_brute_force(spark):
    rng = np.random.default_rng(0)
    rows = [(i, "w " * int(n), s) for i, (n, s) in enumerate(zip(rng.integers(1, 30, 900), rng.choice(["big"] * 7 + ["mid"] * 2 + ["low"], 900), strict=True))]
    df = spark.createDataFrame(rows, "doc_id long, text string, source string").repartition(5)
    out = mixing.mix(df, target=0.9, repeats=3.0).collect()
    sizes = {i: len(t.split()) for i, t, _ in rows}
    per = Counter()
    for i, _, s in rows:
        per[s] += sizes[i]
    planned = {s: (p, rest) for s, _, p, rest in mixing.plan(sorted(per.items()), None, 0.9, 3.0)}
    longest = max(sizes.values())
    taken = Counter()
    for r in out:
        taken[r["source"]] += sizes[r["doc_id"]]
    for s, (p, rest) in planned.items():
        budget = p * per[s] + rest
        assert budget - 1e-6 <= taken[s] <= budget + longest
        times = Counter(r["doc_id"] for r in out if r["source"] == s)
        assert set(times.values()) <= {p, p + 1} and (p == 0 or len(times) == sum(1 for x in rows if x[2] == s))
    again = mixing.mix(df.repartition(2), target=0.9, repeats=3.0).collect()
    assert sorted(out) == sorted(again)
    key = lambda i, p: None  # noqa: E731, F841 - order inside a pass is checked below by prefix sums
    s, (p, rest) = next((s, x) for s, x in planned.items() if x[1] > 0)
    part = {r["doc_id"] for r in out if r["source"] == s and r["pass_no"] == p}
    n_blocks = max(1, -(-sum(1 for x in rows if x[2] == s) // mixing.BLOCK_ROWS))
    place = {r["doc_id"]: r["h"] for r in df.where(F.col("source") == s).select("doc_id", F.xxhash64(F.lit(mixing.SEED), F.lit(p), F.xxhash64("doc_id", "text")).alias("h")).collect()}
    order = sorted(place, key=lambda i: ((place[i] >> 20) % n_blocks, place[i]))
    run, want = 0, set()
    for i in order:
        if run >= rest:
            break
        want.add(i)
        run += sizes[i]
    assert part == want
    for r in out:
        assert r["block_no"] == (r["place"] >> 20) % max(1, -(-sum(1 for x in rows if x[2] == r["source"]) // mixing.BLOCK_ROWS)) and 0 < r["turn"] < 1


def test_op5_rows_are_written_as_a_permutation(spark, monkeypatch):
    monkeypatch.setattr(mixing, "BLOCK_ROWS", 10)
    df = spark.createDataFrame([(i, "w w", "big" if i % 3 else "low") for i in range(600)], "doc_id long, text string, source string")
    mixed = mixing.mix(df, target=0.99, repeats=3.0)
    marks = {(r["doc_id"], r["pass_no"]): (r["pass_no"], r["turn"], r["place"]) for r in mixed.collect()}
    ids = [r["doc_id"] for r in mixing.in_order(mixed, df.columns).collect()]
    want = [i for (i, _), _ in sorted(marks.items(), key=lambda x: x[1])]
    assert ids == want and ids[:600] != sorted(ids[:600])
    kinds = ["big" if i % 3 else "low" for i in ids]
    assert all({"big", "low"} == set(kinds[k : k + 100]) for k in range(0, 500, 100))  # the sources alternate


def test_op5_many_sources_by_aggregates(spark, monkeypatch):
    rng = np.random.default_rng(1)
    df = spark.createDataFrame([(i, "w " * int(rng.integers(1, 9)), f"s{int(rng.pareto(0.6)) % 40}") for i in range(800)], "doc_id long, text string, source string")
    want = sorted(mixing.mix(df, target=0.97, repeats=2.5).collect())
    monkeypatch.setattr(mixing, "BROADCAST_SOURCES", 0)
    assert sorted(mixing.mix(df, target=0.97, repeats=2.5).collect()) == want
    totals = spark.createDataFrame([(float(t),) for t in (1000, 100, 10)], "tokens double")
    for target, repeats in ((0.9, None), (None, 2.0), (0.9, 2.0), (None, None)):
        assert mixing.solve_distributed(totals, 1110.0, target, repeats) == pytest.approx(mixing.solve_exponent(np.array([1000.0, 100, 10]), 1110.0, target, repeats), abs=1e-9)
    with pytest.raises(ValueError):
        mixing.solve_distributed(totals, 5550.0, None, 2.0)


def test_op5_edges(spark, odd):
    out = mixing.mix(odd, target=None, repeats=None, budget=None)
    assert out.columns == [*odd.columns, "pass_no", "block_no", "turn_", "place"]
    assert sorted(map(str, out.select(odd.columns).collect())) == sorted(map(str, odd.collect()))  # clashing columns keep their values
    assert mixing.in_order(out, odd.columns).columns == odd.columns
    assert mixing.mix(odd).count() >= 1
    assert mixing.mix(empty(spark)).count() == 0


# -- 6: ball tree -----------------------------------------------------------------------------------------------------------------
def test_op6_tree_equals_scan():
    rng = np.random.default_rng(2)
    x = np.floor(rng.normal(size=(700, 6)) * 3)
    ids = rng.permutation(700)
    tree = ball.build(ids, x, leaf=16)
    q, qid = x[:50], ids[:50]
    best, who, products = ball.search(tree, qid, q, 5)
    for k in range(50):
        want = sorted((-float(q[k] @ v), int(i)) for i, v in zip(ids, x, strict=True) if i != qid[k])[:5]
        assert [(-s, i) for s, i in zip(best[k], who[k], strict=True)] == want
    assert products < 50 * 700


def test_op6_edges(spark, monkeypatch):
    monkeypatch.setattr(ball, "SHARD", 4)
    monkeypatch.setattr(ball, "BLOCK", 2)
    vecs = [(0, [0.5, 0.5]), (50, [0.5, 0.5]), (50, [0.5, 0.5]), (100, [-0.1, 0.2]), (3, None), (4, [None, 1.0]), (5, [float("nan"), 1.0]), (6, []), (7, [1.0, 2.0, 3.0]), (None, [1.0, 1.0])] + [(i, [i / 60, -i / 90]) for i in range(8, 30)]
    df = spark.createDataFrame(vecs, "vec_id long, embedding array<float>").withColumn("score", F.lit(1))
    rows = ball.top_k(df, F.col("vec_id") % 50 == 0).collect()
    sound = [(i, [math.floor(np.float64(np.float32(x)) * 256) for x in v]) for i, v in vecs if i is not None and v is not None and len(v) == 2 and not any(x is None or x != x for x in v)]
    want = []
    for n, (q, qv) in enumerate(sound):
        if q % 50 == 0:
            ranked = sorted((-sum(a * b for a, b in zip(qv, v, strict=True)), i) for m, (i, v) in enumerate(sound) if m != n)[:5]
            want += [(q, r + 1, i, -s) for r, (s, i) in enumerate(ranked)]
    assert sorted(tuple(r) for r in rows) == sorted(want)
    both = spark.createDataFrame([(0, [1.0, 0.0]), (1, [3.0, 0.0]), (1, [5.0, 0.0])], "vec_id long, embedding array<float>")
    assert sorted(tuple(r)[1:] for r in ball.top_k(both, F.col("vec_id") == 0).collect()) == [(1, 1, 256 * 5 * 256), (2, 1, 256 * 3 * 256)]
    assert ball.top_k(df.limit(0), F.lit(True)).count() == 0


# -- 7: toxicity -------------------------------------------------------------------------------------------------------------------
def toy(n, seed):
    rng = np.random.default_rng(seed)
    clean = ["river", "stone", "cloud", "green", "walk", "house", "quiet", "paper", "window", "table"]
    out = []
    for k in range(n):
        words = list(rng.choice(clean, int(rng.integers(5, 60))))
        bad = k % 4 == 0
        if bad:
            for _ in range(2):
                words.insert(int(rng.integers(len(words))), "vilg" + "".join(rng.choice(list("abcdefgh"), 3)))
        out.append((" ".join(words), float(bad)))
    return out


def test_op7_learns_word_families():
    train, test = toy(600, 1), toy(300, 2)
    model = cnn.fit([t for t, _ in train], np.array([y for _, y in train]), ["en"] * len(train))
    got = cnn.Scorer(model).scores([t for t, _ in test]) >= cnn.CUT
    assert np.mean(got == [bool(y) for _, y in test]) > 0.97
    assert set(model.thresholds) == {"en"}
    start = np.random.default_rng(cnn.SEED).normal(0, 0.1, (cnn.BUCKETS, cnn.DIM)).astype(np.float32)
    used = np.unique(cnn.flat_pieces(["vilgabc", "river"])[0])
    assert np.abs(model.table - start)[used, 1:].max() > 0.05  # the embeddings are trained


def test_op7_reads_all_of_a_long_run():
    train = toy(400, 4)
    model = cnn.fit([t for t, _ in train], np.array([y for _, y in train]))
    a, b = cnn.Scorer(model).logits(["q" * 40 + "vilgabc" * 6, "q" * 82])
    assert cnn.WORD.findall("q" * 41 + "x") == ["q" * 40, "qx"] and a != b


def test_op7_gradients_equal_differences():
    rng = np.random.default_rng(0)
    params = {"embedded": rng.normal(size=(9, cnn.DIM)), "filters": rng.normal(size=(cnn.DIM, cnn.COLUMNS)), "bias": rng.normal(size=(len(cnn.WIDTHS), cnn.FILTERS)), "top": rng.normal(size=len(cnn.WIDTHS) * cnn.FILTERS), "top_bias": np.zeros(1)}
    docs, y, w = [np.array([0, 1, 2, 3, 4]), np.array([5]), np.array([], int)], np.array([1.0, 0, 1]), np.ones(3)

    def loss(p):
        pad, total = max(cnn.WIDTHS), 0.0
        for d, label in zip(docs, y, strict=True):
            x = np.vstack([p["embedded"][d], np.zeros((pad, cnn.DIM))])
            seen, pooled = x @ p["filters"], []
            for k, _ in enumerate(cnn.WIDTHS):
                conv = np.repeat(p["bias"][k][None, :], len(x), 0)
                for j, offset, cols in cnn.LAYOUT:
                    if j == k:
                        conv[: len(x) - offset] += seen[offset:, cols]
                pooled.append(conv.max(0))
            z = np.maximum(np.concatenate(pooled), 0) @ p["top"] + p["top_bias"][0]
            s = 1 / (1 + np.exp(-z))
            total -= label * np.log(s) + (1 - label) * np.log(1 - s)
        return total / len(docs) + 0.5e-4 * ((p["top"] ** 2).sum() + (p["filters"] ** 2).sum())

    grads = cnn._gradients(params, docs, y, w)
    for name in ("filters", "bias", "top", "embedded"):
        for _ in range(6):
            at = tuple(int(rng.integers(n)) for n in params[name].shape)
            up, down = {k: v.copy() for k, v in params.items()}, {k: v.copy() for k, v in params.items()}
            up[name][at] += 1e-5
            down[name][at] -= 1e-5
            assert grads[name][at] == pytest.approx((loss(up) - loss(down)) / 2e-5, abs=1e-5)


def test_op7_batch_scores_equal_single(docs):
    train = toy(200, 3)
    model = cnn.fit([t for t, _ in train], np.array([y for _, y in train]))
    texts = [r["text"] for r in docs.limit(20).collect()] + [None, "", "!!", "vilgabc"]
    together = cnn.Scorer(model).scores(texts)
    assert np.allclose(together, [cnn.Scorer(model).scores([t])[0] for t in texts], atol=1e-6)


def test_op7_query_equals_brute_force(spark):
    docs, labels = table(spark, SF, "documents"), table(spark, SF, "labels")
    model = cnn.train(docs, labels)

    def brute(text):
        words = cnn.WORD.findall((text or "").lower())
        x = [np.mean([model.table[p].astype(float) for p in cnn.flat_pieces([w])[0]], axis=0) for w in words] + [np.zeros(cnn.DIM)] * max(cnn.WIDTHS)
        pooled, at = [], 0
        for k, width in enumerate(cnn.WIDTHS):
            parts = [model.filters[:, at + o * cnn.FILTERS : at + (o + 1) * cnn.FILTERS].astype(float) for o in range(width)]
            at += width * cnn.FILTERS
            pooled += np.max([sum(x[i + o] @ parts[o] for o in range(width)) + model.bias[k] for i in range(len(x) - width + 1)], axis=0).tolist()
        p = 1 / (1 + math.exp(-float(np.maximum(pooled, 0) @ model.top + model.top_bias)))
        return float(model.curve(np.array([p]))[0])

    got = {r["doc_id"]: r["score"] for r in registry.op7_toxicity(spark, SF).collect()}
    for r in docs.orderBy("doc_id").limit(25).collect():
        assert got[r["doc_id"]] == pytest.approx(brute(r["text"]), abs=1e-4)


def test_op7_edges(spark, odd):
    labels = spark.createDataFrame([(1, 1), (3, None), (4, 0), (4, 0), (None, 1), (6, 1), (7, 0), (99, 1)], "doc_id long, toxic int")
    model = cnn.train(odd, labels)
    rows = cnn.score(odd, model).collect()
    assert len(rows) == len(ODD) and all(0 <= r["score"] <= 1 for r in rows)
    assert cnn.keep_clean(odd, model).columns == odd.columns
    assert cnn.score(empty(spark), cnn.train(empty(spark), labels.limit(0))).count() == 0


def test_op7_thresholds_decide_by_language(spark):
    train = toy(200, 3)
    model = cnn.fit([t for t, _ in train], np.array([y for _, y in train]))
    text = train[1][0]
    middle = float(cnn.Scorer(model).scores([text])[0])
    model.thresholds = {"en": middle - 1e-3, "fr": middle + 1e-3}
    df = spark.createDataFrame([(1, text, "xx")], "doc_id long, text string, lang string")
    one = lambda name: ppm.Model([name], [ppm.ContextTree.fit([text])])
    kept = [cnn.keep_clean(df, model, one(name)).count() for name in ("en", "fr", "de")]
    assert kept == [0, 1, int(middle < cnn.CUT)]  # by the predicted language, not the column
    assert cnn.keep_clean(df, model).count() == kept[2]


def test_op7_query(spark):
    rows = registry.op7_toxicity(spark, "/root/testdata/sf0.01").collect()
    assert len(rows) == 1000 and all(r["predicted"] == int(r["score"] >= 0.3) for r in rows)
    truth = {r["doc_id"]: r["toxic"] for r in table(spark, "/root/testdata/sf0.01", "labels").collect()}
    lang = {r["doc_id"]: r["lang"] for r in table(spark, "/root/testdata/sf0.01", "documents").select("doc_id", "lang").collect()}
    kept = [r for r in rows if r["held_out"] and r["doc_id"] in truth and lang[r["doc_id"]] == "en"]
    assert np.mean([r["predicted"] == truth[r["doc_id"]] for r in kept]) > 0.93


# -- 8: licences -------------------------------------------------------------------------------------------------------------------
def test_op8_equals_brute_force(spark):
    docs = table(spark, "/root/testdata/sf0.01", "documents")
    idf, units_of = licenses.vectors()
    rare = math.log(1 + len(licenses.TEMPLATES)) + 1

    longest, chars = licenses.lengths()[-1], max(len(t) for _, t in licenses.TEMPLATES)
    cue = re.compile(licenses.TRIGGER)

    def best(text):
        lowered, found = (text or "").lower(), []
        segments = [x for x in re.split(r"[\n\r]+|(?<=[.!?;:])\s+", lowered) if re.search("[a-z0-9]", x)]
        units = set()
        for i, x in enumerate(segments):
            if cue.search(x) or i + 1 < len(segments) and cue.search(segments[i + 1]):
                run = re.findall(licenses.TOKEN, " ".join(segments[i : i + longest]))[:longest]
                units |= {tuple(run[:n]) for n in [len(re.findall(licenses.TOKEN, x)), *licenses.lengths()] if n <= len(run)}
        if cue.search(lowered) and len(lowered) <= 2 * chars:
            units.add(tuple(re.findall(licenses.TOKEN, lowered)))
        for unit in units:
            w = {t: (1 + math.log(n)) * idf.get(t, rare) for t, n in Counter(unit).items()}
            norm = math.sqrt(sum(x * x for x in w.values()))
            for name, own in units_of:
                dot = sum(x * own.get(t, 0.0) for t, x in w.items())
                if norm and round(dot / norm, 6) >= licenses.LEAST:
                    found.append((-round(dot / norm, 6), -len(unit), name))
        return min(found, default=None)

    want = {r["doc_id"]: best(r["text"]) for r in docs.collect()}
    rows = registry.op8_licenses(spark, "/root/testdata/sf0.01").collect()
    assert len(rows) == len(want) and sum(x is not None for x in want.values()) > 5
    for r in rows:
        own = want[r["doc_id"]]
        assert (r["origin"] == "own") == (own is not None)
        if own:
            assert (r["license"], r["score"]) == (own[2], pytest.approx(-own[0], abs=2e-6))


def test_op8_headers_wrapped_notices_and_full_texts(spark):
    import textwrap

    text = dict((n, t) for n, t in licenses.TEMPLATES if len(t) > 600)
    header = next(t for n, t in licenses.TEMPLATES if n == "GPL-3.0" and t.startswith("This program is free"))
    rows = {
        "a/x.py": "\n".join("# " + x for x in textwrap.wrap(header, 60)) + "\n\nimport os\n" + "code line here\n" * 40,
        "b/mit.txt": "The MIT License\n\nCopyright (c) 2001 A Person\n\n" + textwrap.fill(text["MIT"], 70), "b/other.c": "int main() {}",
        "c/x.c": "/* Some words of mine. Released under the MIT License. More words of mine follow here. */", "d/y.rs": "// SPDX-License-Identifier: ISC\nfn main() {}",
        "e/COPYING": "  GNU GENERAL PUBLIC LICENSE\n  Version 3, 29 June 2007\n" + "Preamble words that nobody has listed among the templates of this test.\n" * 30, "e/z.c": "x",
    }
    df = spark.createDataFrame(list(rows.items()), "path string, text string").withColumn("doc_id", F.monotonically_increasing_id())
    got = {r["path"]: (r["license"], r["origin"]) for r in licenses.scan(df, F.col("path")).collect()}
    assert got["a/x.py"] == ("GPL-3.0", "own") and got["b/mit.txt"] == ("MIT", "own") and got["b/other.c"] == ("MIT", "inherited")
    assert got["c/x.c"] == ("MIT", "own") and got["d/y.rs"] == ("ISC", "own") and got["e/COPYING"] == ("GPL-3.0", "own") and got["e/z.c"] == ("GPL-3.0", "inherited")


def test_op8_inheritance(spark):
    rows = [("a/LICENSE", "Released under the MIT License."), ("a/x/y/f.py", "nothing here"), ("a/x/LICENSE", "Licensed under the Apache License, Version 2.0."), ("b/f.py", "none"), ("a/g.py", "# This work is licensed under the GNU General Public License, version 3.\n" + "code\n" * 50), ("a/x/z.py", None), (None, "text"), ("b/f.py", "none")]
    df = spark.createDataFrame([(i, p, t) for i, (p, t) in enumerate(rows)], "doc_id long, path string, text string").withColumn("license", F.lit("clash"))
    got = {r["doc_id"]: (r["license"], r["origin"], r["from_dir"]) for r in licenses.scan(df, F.col("path")).collect()}
    assert got[0] == ("MIT", "own", None) and got[1] == ("Apache-2.0", "inherited", "a/x") and got[5] == ("Apache-2.0", "inherited", "a/x")
    assert got[4][:2] == ("GPL-3.0", "own") and got[3] == got[7] == (None, None, None) and got[6] == (None, None, None)
    doubled = licenses.scan(df.unionByName(df), F.col("path"))
    assert doubled.count() == 16
    assert licenses.scan(df.limit(0), F.col("path")).count() == 0


def test_op8_every_template_is_triggered_at_its_start():
    for _, text in licenses.TEMPLATES:
        first = re.split(r"(?<=[.!?;:])\s+", text.lower())
        assert any(re.search(licenses.TRIGGER, x) for x in first[:2])


def test_op8_plan_is_native(spark):
    df = registry.op8_licenses(spark, SF)
    plan = df._jdf.queryExecution().toString()
    assert not re.search("Python|Arrow|Pandas", plan)


# -- 9: BPE ---------------------------------------------------------------------------------------------------------------------
@pytest.fixture(scope="module")
def encoding():
    return tiktoken.Encoding("own", pat_str=public_tokenizers.PATTERN, mergeable_ranks=bpe.read_ranks(RANKS), special_tokens={})


def test_op9_equals_the_library(spark, docs, encoding):
    rows = {r["doc_id"]: r for r in registry.op9_bpe(spark, SF).collect()}
    for r in docs.collect():
        ids = encoding.encode_ordinary(r["text"] or "")
        got = rows[r["doc_id"]]
        assert got["n_tokens"] == len(ids) and got["ids_sha256"] == hashlib.sha256(np.array(ids, "<u4").tobytes()).hexdigest()
        assert got["decoded_sha256"] == hashlib.sha256((r["text"] or "").encode()).hexdigest()


def test_op9_hard_words(encoding):
    ranks = bpe.read_ranks(RANKS)
    coder = bpe.WordCoder(ranks, bpe.merge_table(ranks))
    rng = np.random.default_rng(1)
    words = regex.findall(public_tokenizers.PATTERN, "a" * 300 + " " + "".join(rng.choice(list("abcdefgh"), 700)) + " 日本語日本 \U0001f600 <|endoftext|> don't \n\n  x  y " + "é" * 90)
    for w in words:
        ids, _, raw, _ = coder.encode([w])
        assert ids.tolist() == encoding.encode_ordinary(w) and raw.tobytes() == w.encode()


@pytest.mark.parametrize("text", ["".join(np.random.default_rng(0).choice(list("abcdefghijklmnopqrstuvwxyz"), 200_000)), "a" * 200_000, "ab" * 20_000, "".join(np.random.default_rng(1).choice(list("ab"), 9000)), "".join(np.random.default_rng(2).choice(["the", "ing", "er", "on", "an", "re", "st"], 3000))])
def test_op9_very_long_words(encoding, text):
    ranks = bpe.read_ranks(RANKS)
    coder = bpe.WordCoder(ranks, bpe.merge_table(ranks))
    began = time.time()
    ids, n, raw, size = coder.encode([text])
    assert time.time() - began < 20
    assert ids.tolist() == encoding.encode_ordinary(text) and raw.tobytes() == text.encode() and n.tolist() == [len(ids)] and size.tolist() == [len(text)]


def test_op9_long_form_goes_back_where_ranks_fall(monkeypatch):
    """A vocabulary in which a contraction makes a pair of a lower rank: places must then go one at a time."""
    ranks = {bytes([b]): b for b in range(256)} | {b"xab": 256, b"ab": 257, b"xabx": 258, b"bx": 259}
    coder = bpe.WordCoder(ranks, bpe.merge_table(ranks))
    text = "xabxabxxabab" * 30
    own = tiktoken.Encoding("own", pat_str=r"[\s\S]+", mergeable_ranks=ranks, special_tokens={})
    assert coder.encode([text])[0].tolist() == own.encode_ordinary(text)


def test_op9_forgets_and_goes_on(encoding, monkeypatch):
    monkeypatch.setattr(bpe, "WORDS_KEPT", 3)
    monkeypatch.setattr(bpe, "PIECES_KEPT", 3)
    ranks = bpe.read_ranks(RANKS)
    coder = bpe.WordCoder(ranks, bpe.merge_table(ranks))
    for text in ("zyxwab qwerti", "zyxwab other wordsy", "again zyxwab qwerti", ""):
        words = regex.findall(public_tokenizers.PATTERN, text)
        assert coder.encode(words)[0].tolist() == encoding.encode_ordinary(text)


def test_op9_latin_pattern_equals_the_given_one():
    fast, slow = bpe.latin_pattern(public_tokenizers.PATTERN), regex.compile(public_tokenizers.PATTERN)
    rng = np.random.default_rng(0)
    for _ in range(300):
        text = "".join(chr(c) for c in rng.integers(1, 256, 60)) + "it's  we'll   \n x²½ÿ "
        assert fast.findall(text) == slow.findall(text)
    assert bpe.latin_pattern(r"\p{Lu}+") is None and bpe.latin_pattern(r"(?i:a)|\w") is None


def test_op9_round_trip_and_edges(spark, odd, encoding):
    full = bpe.encode(odd, RANKS, public_tokenizers.PATTERN)
    rows = {r["doc_id"]: r for r in full.collect()}
    assert rows[1]["n_tokens"] == rows[2]["n_tokens"] == 0 and rows[1]["ids"] == []
    assert rows[7]["ids"] == encoding.encode_ordinary(ODD[7][1]) and rows[7]["decoded"] == ODD[7][1]
    back = {r["doc_id"]: r["text"] for r in bpe.decode(full, RANKS).collect()}
    assert back[6] == ODD[6][1] and back[7] == ODD[7][1] and back[1] == ""
    assert bpe.encode(empty(spark), RANKS, public_tokenizers.PATTERN).count() == 0
    with pytest.raises(Exception, match="not in the vocabulary"):
        bpe.decode(spark.createDataFrame([(1, [60000])], "doc_id long, ids array<int>"), RANKS).collect()


# -- 10: chat -------------------------------------------------------------------------------------------------------------------
T = "array<struct<role:string,content:string>>"


def test_op10_prefix_and_spans(spark):
    a = [("user", "hi"), ("assistant", "yes"), ("user", "more"), ("assistant", "été")]
    b = [("user", "hi"), ("assistant", "yes"), ("assistant", "no")]
    cases = [(1, a, b), (2, a, a), (3, a, []), (4, None, b), (5, [("user", None), None, (None, "x")], [("user", "")]), (6, a, a[:2])]
    df = spark.createDataFrame(cases, f"k long, chosen {T}, rejected {T}").withColumn("prompt", F.lit("clash"))
    got = {r["k"]: r for r in chat.preference(df, ["k"]).collect()}
    show = lambda turns: "".join(f"<|{r}|>\n{c}<|end|>\n" for r, c in turns)
    assert got[1]["n_common"] == 2 and got[1]["prompt"] == show(a[:2]) and got[1]["chosen"] == show(a[2:]) and got[1]["rejected"] == show(b[2:])
    for side, turns in (("chosen", a[2:]), ("rejected", b[2:])):
        text = got[1][side]
        assert [text[s["start"] : s["stop"]] for s in got[1][f"{side}_spans"]] == [c + "<|end|>\n" for r, c in turns if r == "assistant"]
    assert got[2]["n_common"] == 4 and got[2]["chosen"] == got[2]["rejected"] == "" and got[2]["chosen_spans"] == []
    assert got[3]["prompt"] == "" and got[3]["rejected"] == "" and got[4]["chosen"] == "" and got[4]["rejected"] == show(b)
    assert got[5]["n_common"] == 1 and got[5]["chosen"] == show([("user", "x")])
    assert got[6]["n_common"] == 2 and got[6]["rejected"] == "" and got[6]["chosen"] == show(a[2:])


def test_op10_conversation_edges(spark):
    rows = [(1, 2, "assistant", "b"), (1, 1, "user", "a"), (1, None, None, None), (1, 2, "assistant", "b"), (None, 1, "user", "x"), (0, 1, "assistant", "z"), (5, 1, "user", "alone")]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("turns", F.lit(1))
    convs = {r["conv_id"]: [tuple(t) for t in r["turns"]] for r in chat.conversations(df).collect()}
    assert convs.pop(None) == [("user", "x")]
    assert convs == {1: [("user", ""), ("user", "a"), ("assistant", "b"), ("assistant", "b")], 0: [("assistant", "z")], 5: [("user", "alone")]}
    pairs = {r["conv_id"]: [tuple(t) for t in r["rejected"]] for r in chat.reply_swaps(chat.conversations(df)).collect()}
    assert pairs[1] == [("user", ""), ("user", "a"), ("assistant", "b"), ("assistant", "z")] and pairs[0] == [("assistant", "b")] and pairs[5] == [("user", "alone")]
    assert chat.preference(chat.reply_swaps(chat.conversations(df.limit(0))), ["conv_id"]).count() == 0


def test_op10_plan_is_native(spark):
    assert not re.search("Python|Arrow|Pandas", registry.op10_preference(spark, SF)._jdf.queryExecution().toString())


# -- 4: the pipeline's stage: similarity of five-word shingle sets ---------------------------------------------------------------
def test_op4_similar_finds_copies_and_leaves_the_rest(spark):
    rng = np.random.default_rng(3)
    words = [f"w{k}" for k in range(4000)]
    rows, group = [], {}
    for k in range(40):
        base = list(rng.choice(words, int(rng.integers(80, 400))))
        rows.append((k * 10, " ".join(base)))
        for c in range(1, 4):
            near = list(base)
            for at in rng.choice(len(near), max(1, len(near) // 100), replace=False):
                near[at] = "edited"
            rows.append((k * 10 + c, " ".join(near)))
            group[k * 10 + c] = k * 10
        other = base[: len(base) // 3] + list(rng.choice(words, 2 * len(base) // 3))
        rows.append((k * 10 + 5, " ".join(other)))
    df = spark.createDataFrame(rows, "doc_id long, text string")
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar(df).collect()}
    found = sum(got[i] == b for i, b in group.items())
    assert found >= 0.95 * len(group)
    assert all(got[k * 10 + 5] == k * 10 + 5 for k in range(40))
    kept = {r["doc_id"] for r in simhash.keep_one(df).collect()}
    assert kept == {i for i, c in got.items() if i == c}


def test_op4_wide_fingerprint_follows_similarity():
    rng = np.random.default_rng(4)
    for share in (0.02, 0.05):
        base = [f"v{k}" for k in range(3000)]
        near = list(base)
        for at in rng.choice(3000, int(3000 * share), replace=False):
            near[at] = "x" + str(at)
        a, b = (simhash.shingle_set(" ".join(t)) for t in (base, near))
        j = len(np.intersect1d(a, b)) / len(np.union1d(a, b))
        want = 256 * simhash.differing_share(j)
        assert abs(int(simhash.differing(simhash.wide_fingerprint(a)[None], simhash.wide_fingerprint(b)[None])[0]) - want) < 4 * np.sqrt(want)


def at_similarity(rng, low, high, words=400):
    """A text, and an edited copy whose exact similarity of five-word shingle sets lies in [low, high)."""
    shingles = lambda t: {" ".join(t[i : i + 5]) for i in range(len(t) - 4)}
    while True:
        base = [f"u{x}" for x in rng.integers(0, 1 << 40, words)]
        near = list(base)
        for at in rng.permutation(words):
            near[at] = "edited"
            a, b = shingles(base), shingles(near)
            j = len(a & b) / len(a | b)
            if low <= j < high:
                return " ".join(base), " ".join(near)
            if j < low:
                break


def pairs_at(spark, low, high, n=150):
    rng = np.random.default_rng(8)
    rows = [(2 * k + side, t) for k in range(n) for side, t in enumerate(at_similarity(rng, low, high))]
    return spark.createDataFrame(rows, "doc_id long, text string")


def test_op4_similar_finds_isolated_pairs_at_the_threshold(spark):
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar(pairs_at(spark, 0.8, 0.83)).collect()}
    assert all(got[2 * k + 1] == got[2 * k] == 2 * k for k in range(150))


@pytest.mark.parametrize("part", [simhash.PART, 20])
def test_op4_similar_large_group_is_whole(spark, monkeypatch, part):
    monkeypatch.setattr(simhash, "PART", part)
    rng = np.random.default_rng(9)
    base = [f"g{k}" for k in range(200)]
    texts = []
    for _ in range(120):
        near = list(base)
        for at in rng.choice(200, int(rng.integers(1, 9)), replace=False):
            near[at] = f"e{rng.integers(1 << 40)}"
        texts.append(" ".join(near))
    sets = [set(simhash.shingle_set(t).tolist()) for t in texts]
    label = list(range(len(texts)))
    for i in range(len(texts)):
        for j in range(i):
            if len(sets[i] & sets[j]) >= 0.8 * len(sets[i] | sets[j]) and label[i] != label[j]:
                low, high = sorted((label[i], label[j]))
                label = [low if x == high else x for x in label]
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(len(texts))] == label


def test_op4_similar_leaves_pairs_under_the_threshold(spark):
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar(pairs_at(spark, 0.76, 0.795)).collect()}
    assert all(i == c for i, c in got.items())


@pytest.mark.parametrize("k", simhash.NEAREST)
def test_op4_similar_short_sets_meet_without_a_radius_in_all_rounds(spark, k):
    prints = [bytes(32), bytes(32), b"\xff" * 32]  # 256 differing bits: far outside the radius
    for n, want in ((10, {(0, 2), (1, 2)}), (1000, set())):
        met = spark.createDataFrame([(1, 1, 0, node, n, fp) for node, fp in enumerate(prints)], "key long, parts int, part int, node long, n int, fp binary")
        found = spark.createDataFrame([(0, 0), (1, 0)], "node long, component long")
        pairs = {tuple(r) for r in simhash._round(met, found, None, k, simhash.SIMILARITY, simhash.FEW).collect()}
        assert (pairs == want) if k != 1 else (pairs == ({(0, 2)} if want else set()))


def near_misses(n, words=200):
    """Texts made of one by edits at places of their own: most pairs lie within the radius, few have the similarity."""
    rng = np.random.default_rng(10)
    base = [f"g{k}" for k in range(words)]
    texts = []
    for _ in range(n):
        near = list(base)
        for at in rng.choice(words, int(rng.integers(3, 7)), replace=False):
            near[at] = f"e{rng.integers(1 << 40)}"
        texts.append(" ".join(near))
    return texts


@pytest.mark.parametrize("most", [simhash.MOST, 1 << 14])
def test_op4_similar_looks_at_near_misses_without_a_row_for_each(spark, monkeypatch, most):
    monkeypatch.setattr(simhash, "MOST", most)
    texts, rows = near_misses(160), []
    checked = simhash._checked
    monkeypatch.setattr(simhash, "_checked", lambda pairs, *a: rows.append(pairs.count()) or checked(pairs, *a))
    sets = [simhash.shingle_set(t) for t in texts]
    label = list(range(len(texts)))
    for i, a in enumerate(sets):
        for j, b in enumerate(sets[:i]):
            same = len(np.intersect1d(a, b))
            if same >= 0.8 * (len(a) + len(b) - same) and label[i] != label[j]:
                low, high = sorted((label[i], label[j]))
                label = [low if x == high else x for x in label]
    got = {r["doc_id"]: r["component_id"] for r in simhash.similar(spark.createDataFrame(list(enumerate(texts)), "doc_id long, text string")).collect()}
    assert [got[i] for i in range(len(texts))] == label
    assert 1 < len(set(label)) < len(texts)
    assert len(rows) == len(simhash.NEAREST) and None not in simhash.NEAREST  # each sends some of a member; the rest meets in tasks


def test_op4_similar_short_sets_meet_without_a_radius_in_the_last_round(spark):
    prints = [bytes(32), bytes(32), b"\xff" * 32]
    sets = spark.createDataFrame([(k, list(range(10))) for k in range(3)], "node long, shingles array<long>")
    for n, want in ((10, 1), (1000, 0)):
        met = spark.createDataFrame([(1, 1, 0, node, n, fp) for node, fp in enumerate(prints)], "key long, parts int, part int, node long, n int, fp binary")
        found = spark.createDataFrame([(0, 0), (1, 0)], "node long, component long")
        assert simhash._rest(met, found, sets, simhash.SIMILARITY, simhash.FEW).count() == want
