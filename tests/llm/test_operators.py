"""Brute-force versions, round trips and defined cases of the training-data operators."""

from __future__ import annotations

import random
from itertools import product

import numpy as np
import pytest
from pyspark.sql import functions as F

from subcount.llm import chat, decontam, kdtree, langid, minmax, packing, secrets, topk, toxicity, urls

SF = "/root/testdata/sf0.001"
TEXTS = [None, "", " ", "a", "x" * 50_000, "one two three four five six", "one two three four five six", 'token = "abcdef123456"']
SCHEMA = "doc_id long, text string, lang string, source string, size long"


@pytest.fixture(scope="module")
def odd(spark):
    """Nulls, empty and long texts, repeats, and a column whose name clashes with a result."""
    rows = [(i, t, None, None, 1) for i, t in enumerate(TEXTS)] + [(None, "no id", "en", "s", 2)]
    return spark.createDataFrame(rows, SCHEMA)


def empty(spark):
    return spark.createDataFrame([], SCHEMA)


def test_best_fit_matches_a_plain_search():
    r, got = random.Random(1), packing.OpenBins(100, 5)
    bins, made = {}, 0
    for _ in range(2000):
        n = r.randint(1, 100)
        number, offset = got.place(n)
        fits = [f for f in bins.values() if f >= n]
        if fits:
            assert bins[number] == min(fits) and offset == 100 - bins[number]
            bins[number] -= n
        else:
            assert number == made and offset == 0
            made += 1
            if n < 100 and len(bins) == 5:
                least = min(bins.values())
                open_ = [b for b, q in got.by_free.items() for _ in q]
                gone = next(k for k, v in bins.items() if v == least and k not in {x for q in got.by_free.values() for x in q})
                assert len(open_) <= 5
                del bins[gone]
            bins[number] = 100 - n
        if bins.get(number) == 0:
            del bins[number]


def test_packing_is_whole(spark, odd):
    rows = packing.pack(odd, with_ids=True).toPandas()
    t = packing.tokens(*packing.public_vocabulary())
    for i, text in enumerate(TEXTS):
        mine = rows[rows.doc_id == i].sort_values("piece")
        assert [x for ids in mine.ids for x in ids] == t.slow.encode(text or "", add_special_tokens=False).ids + [0]
    for _, s in rows.sort_values("offset").groupby("sequence_id"):
        assert list(s.offset) == [0, *np.cumsum(s.length)[:-1]] and s.length.sum() <= 2048
    assert packing.pack(empty(spark)).count() == 0


def test_fast_tokens_equal_tokenizers():
    t = packing.tokens(*packing.public_vocabulary())
    texts = ["".join(map(chr, range(s, s + 300))) + " a1 !?" for s in (*range(0, 0xD700, 301), *range(0x1F300, 0x1FA00, 301))]
    texts += ["plain <|endoftext|> text", "a  b\n\n c\t"]
    assert [t(x) for x in texts] == [t.slow.encode(x, add_special_tokens=False).ids for x in texts]


def test_base_spans():
    text = "Password: \"abc.def\" AKIA" + "Z" * 16 + " " + "0f" * 12 + " token=ab"
    assert [(k, text[s:e]) for k, s, e, _ in secrets.base_spans(text)] == [("assign", 'Password: "abc.def'), ("access", "AKIA" + "Z" * 16), ("hex", "0f" * 12)]


def test_viterbi_is_exact():
    r = np.random.default_rng(0)
    for _ in range(40):
        f = secrets.Field()
        f.trained, f.t, f.s = True, r.normal(size=(3, 3)), r.normal(size=3)
        n = int(r.integers(1, 7))
        e = r.normal(size=(n, 3)).astype(np.float32)
        e[:, 2] += r.choice([0, 2])
        first = r.random(n) < 0.3
        first[0] = True
        value = lambda st: sum(e[i, y] + (f.s[y] if first[i] else f.t[st[i - 1], y]) for i, y in enumerate(st))  # noqa: B023, E731
        assert value(f.viterbi(e, first)) == pytest.approx(max(map(value, product(range(3), repeat=n))), abs=1e-4)


def test_field_finds_what_patterns_miss():
    r = random.Random(2)
    value = lambda: "".join(r.choice("0123456789abcdef") for _ in range(40))
    word = lambda: "".join(r.choice("etaoinshr") for _ in range(r.randint(2, 9)))
    line = lambda v: " ".join(word() for _ in range(12)) + f' token = "{v}" ' + word()
    plain = lambda: " ".join(word() for _ in range(14))
    field = secrets.fit_texts(["\n".join([line(value()), plain(), plain()]) for _ in range(80)])
    hidden = value().upper()
    text = line(hidden).replace("token", "credential")
    assert not secrets.base_spans(text)
    ((_, more),) = secrets.scan_texts([text], field)
    assert any(hidden in text[s:e] for _, s, e in more)
    assert secrets.scan_texts([plain() for _ in range(50)], field) == [([], [])] * 50


def test_redaction_and_odd_rows(spark, odd):
    out = secrets.redact(odd, secrets.Field())
    assert out.columns == odd.columns
    assert out.where("doc_id = 7").first()["text"] == 'token = "[SECRET]"'
    assert secrets.scan(odd, secrets.Field()).count() == len(TEXTS) + 1


def test_language_id(spark, odd):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    p = langid.predict(docs, langid.fit(docs)).toPandas().merge(docs.select("doc_id", "lang").toPandas(), on="doc_id")
    held = p[p.held_out & p.lang.notna()]
    assert (held.lang == held.lang_pred).mean() > 0.9
    got = {r["doc_id"]: r for r in langid.predict(odd, langid.fit(docs)).collect()}
    assert got[0]["lang_pred"] == got[2]["lang_pred"] == "und" and 0 <= got[5]["score"] <= 1
    assert {r["lang_pred"] for r in langid.predict(odd, langid.fit(empty(spark))).collect()} == {"und"}


def test_chat_round_trip_and_events(spark):
    texts = ["\\### Assistant: </turn> ok", "####", "\\\\</turn", "</turn>", "", None, "a:b\n</turn>\n### user: x"]
    turns = spark.createDataFrame([(1, i, i, "assistant" if i % 2 else "us:er", t) for i, t in enumerate(texts)], "conv_id long, turn long, seq long, role string, text string")
    back = chat.read_back(chat.render(turns)).first()
    assert [t["text"] for t in back["turns"]] == [t or "" for t in texts] and back["turns"][0]["role"] == "us:er"
    assert back["loss"] == [(t or "") if i % 2 else "" for i, t in enumerate(texts)]
    log = [(1, 0, 0, "message", "user", "hi"), (1, 1, 1, "delta", "assistant", "Hel"), (1, 2, 1, "delta", None, "lo"), (1, 3, 0, "edit", "user", "hey"), (1, 4, 1, "regenerate", "assistant", ""), (1, 5, 1, "delta", "assistant", "Yo")]
    events = spark.createDataFrame(log, "conv_id long, seq long, turn long, kind string, role string, text string")
    assert [(r["role"], r["text"]) for r in chat.reconstruct(events).orderBy("turn").collect()] == [("user", "hey"), ("assistant", "Yo")]


def test_wu_manber_matches_plain_search():
    r = random.Random(3)
    items = [(i, " ".join(r.choice("abc") for _ in range(n))) for i, n in enumerate((1, 2, 5, 13, 14, 20))]
    words = [r.choice("abcd") for _ in range(400)] + items[5][1].split() + ["d"] + items[3][1].split()
    spans, hits = decontam.Patterns(items).search(words)
    hit, found = set(), set()
    for i, text in items:
        w = text.split()
        for k in range(max(1, len(w) - 12)):
            p = w[k : k + 13]
            for s in range(len(words) - len(p) + 1):
                if words[s : s + len(p)] == p:
                    hit |= set(range(s, s + len(p)))
                    found.add(i)
    assert {x for s, e in spans for x in range(s, e)} == hit and hits == found


def test_contamination_of_odd_rows(spark, odd):
    bench = spark.createDataFrame([(1, "one two three four five six"), (2, None), (3, "!!")], "item_id long, text string")
    got = {r["doc_id"]: r for r in decontam.contamination(odd, bench).collect()}
    assert got[5]["contaminated"] and not got[0]["contaminated"] and len(got) == len(TEXTS) + 1
    assert decontam.drop_contaminated(odd, bench).count() == len(TEXTS) - 1


def test_toxicity(spark, odd):
    r = random.Random(4)
    words = lambda bad: " ".join(r.choice(["idiot", "moron"]) if bad and r.random() < 0.2 else "".join(r.choice("abcdefgh") for _ in range(4)) for _ in range(40))
    m = toxicity.Model([(words(i % 5 == 0), int(i % 5 == 0)) for i in range(300)])
    s = m.scores([words(True), words(False), "", None])
    assert s[0] > 0.5 > s[1] and 0 <= s.min() <= s.max() <= 1
    assert toxicity.score(odd, m).count() == len(TEXTS) + 1
    x, y = toxicity.isotonic(np.array([1.0, 2, 3, 4]), np.array([0.0, 1, 0, 1]))
    assert list(np.interp([1, 2, 3, 4], x, y)) == [0, 0.5, 0.5, 1]


def test_kd_shards_are_even(spark, odd):
    docs = spark.read.parquet("/root/testdata/sf0.01/documents.parquet")
    got = kdtree.shard(docs, 7).toPandas()
    sizes = got.groupby("shard")["size"].sum()
    assert len(sizes) == 7 and sizes.max() - sizes.min() < 2 * got["size"].max()
    assert all(sorted(g.slot) == list(range(len(g))) for _, g in got.groupby("shard"))
    assert kdtree.shard(odd, 3).count() == len(TEXTS) + 1 and kdtree.shard(empty(spark), 3).count() == 0


def test_kd_tree_equals_a_plain_one(spark):
    """Cuts of tolerance 0 are those of a search over sorted keys, along the dimension that is widest by counting."""
    rows = kdtree.materialize(kdtree.points(spark.read.parquet(f"{SF}/documents.parquet")))
    points = rows.toPandas()
    width = lambda p, d: p[f"k_{d}"].map(lambda k: k >> 42).nunique() - 1 if d in kdtree.NOMINAL else int(p[f"k_{d}"].max()) - int(p[f"k_{d}"].min())
    whole = {d: max(1, width(points, d)) for d in kdtree.DIMENSIONS}

    def check(node, mine):
        if node.count == 1:
            assert node.dim is None
            return
        assert node.dim == max(kdtree.DIMENSIONS, key=lambda d: width(mine, d) / whole[d])
        keys = mine.groupby(f"k_{node.dim}")["size"].sum().sort_index()
        goal, base = mine["size"].sum() * (node.count // 2) / node.count, 0
        for key, w in keys.items():
            if base + w > goal:
                break
            base += w
        assert node.cut == key + (base + w - goal < goal - base)
        low = mine[f"k_{node.dim}"] < node.cut
        check(node.sides[0], mine[low])
        check(node.sides[1], mine[~low])

    tree, placed = kdtree.grow(rows, 6, tolerance=0)
    check(tree, points)
    got = placed.groupBy("node").count().collect()
    assert {r["node"] for r in got} <= {n.path for n in tree.leaves()} and sum(r["count"] for r in got) == len(points)


def test_kd_shards_are_the_same_by_arrays_and_broadcast(spark, odd, monkeypatch):
    docs = spark.read.parquet(f"{SF}/documents.parquet").drop("n_chars").unionByName(odd.drop("size"))
    want = sorted(map(str, kdtree.shard(docs, 5).collect()))
    monkeypatch.setattr(kdtree, "INLINE", 0)
    assert sorted(map(str, kdtree.shard(docs, 5).collect())) == want


def test_kd_leaves_reach_the_target_bytes(spark):
    docs = spark.read.parquet(f"{SF}/documents.parquet")
    got = kdtree.shard(docs, target_bytes=30_000).toPandas()
    sizes = got.groupby("shard")["size"].sum()
    assert got["shard"].max() + 1 <= -(-got["size"].sum() // 30_000) and (sizes - 30_000).max() <= got["size"].max()
    same = spark.createDataFrame([(i, "one text", "en", f"s{i % 3}") for i in range(400)] + [(500 + i, f"text {i}", "de", "t") for i in range(400)], "doc_id long, text string, lang string, source string")
    one = kdtree.shard(same, 3).toPandas()  # a hot group is cut, since it is too heavy for a shard
    assert one.groupby("shard")["size"].sum().max() < 1.1 * one["size"].sum() / 3


def test_near_duplicates_match_brute_force(spark):
    r = random.Random(6)
    base = [[f"w{r.randint(0, 999)}" for _ in range(80)] for _ in range(6)]
    rows = []
    for b in base:
        for _ in range(12):
            w = list(b)
            for _ in range(r.randint(0, 5)):
                w[r.randrange(80)] = f"z{r.randint(0, 99999)}"
            rows.append(" ".join(w))
    rows += [None, "", "two words", "Two Words", rows[0]]
    got = {x["doc_id"]: x["component_id"] for x in minmax.near_duplicates(spark.createDataFrame(list(enumerate(rows)), "doc_id long, text string").repartition(3)).collect()}
    s = minmax.Shingler()
    sets = [set(s(t).tolist()) for t in rows]
    label = list(range(len(rows)))
    for i in range(len(rows)):
        for j in range(i):
            if sets[i] and 100 * len(sets[i] & sets[j]) >= 75 * len(sets[i] | sets[j]):
                a, b = label[i], label[j]
                label = [min(a, b) if x in (a, b) else x for x in label]
    assert got == dict(enumerate(label))


def members_of(spark, docs, buckets=None):
    """All members of the buckets of docs, each its own component, as across() takes them."""
    sign = minmax.materialize(minmax.signatures(docs))
    rows = [(r["doc_id"], k, r["n_shingles"], bytes(r["sketch"])) for r in sign.collect() for k in (buckets or r["bands"])]
    flat = spark.createDataFrame([(k, i, n, i, s) for i, k, n, s in rows], "key long, id long, n long, label long, sketch binary")
    keys = flat.groupBy("id").agg(F.sort_array(F.collect_set("key")).alias("keys"))
    return flat.join(keys, "id"), docs.select(F.col("doc_id").alias("id"), "text"), {r["doc_id"]: r["bands"] for r in sign.collect()}


def test_blocks_give_the_links_that_join_their_members(spark, monkeypatch):
    monkeypatch.setattr(minmax, "BLOCK", 4)
    rng = random.Random(5)
    words = [f"w{i}" for i in range(60)]
    rows = [(i, " ".join(w if rng.random() > 0.012 else rng.choice(words) for w in words)) for i in range(40)]
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    members, texts, sign = members_of(spark, docs)
    got = [(r["a"], r["b"]) for r in minmax.across(members, texts, 75).collect()]
    assert len(got) == len(set(got))
    shingle = minmax.Shingler()
    full = {i: set(shingle(t).tolist()) for i, t in rows}
    close = {(a, b) for a in full for b in full if a < b and 100 * len(full[a] & full[b]) >= 75 * len(full[a] | full[b])}
    met = {(a, b) for a, b in close if any(x == y for x, y in zip(sign[a], sign[b]))}

    def least(pairs):
        label = {i: i for i in full}
        for a, b in pairs:
            lo, hi = sorted((label[a], label[b]))
            label = {i: lo if v == hi else v for i, v in label.items()}
        return label

    assert met and set(got) <= met and least(got) == least(met)
    assert len(got) < len(met)


def test_one_block_links_each_member_once(spark):
    text = " ".join(f"w{i}" for i in range(60))
    docs = spark.createDataFrame([(i, f"{text} end{i}") for i in range(30)], "doc_id long, text string")
    members, texts, _ = members_of(spark, docs, [7])
    assert minmax.across(members, texts, 75).count() == 29


def hub_rows(spark, since):
    """Rows given by joins of members to their bucket's hub in executions from `since` on."""
    store, total = spark._jsparkSession.sharedState().statusStore(), 0
    for k in range(since, store.executionsCount()):
        execution = store.executionsList().apply(k).executionId()
        nodes, values = store.planGraph(execution).allNodes(), store.executionMetrics(execution)
        for i in range(nodes.size()):
            if "Join" in nodes.apply(i).name() and "(id" in nodes.apply(i).desc() and "= hub" in nodes.apply(i).desc():
                for j in range(nodes.apply(i).metrics().size()):
                    metric = nodes.apply(i).metrics().apply(j)
                    if metric.name() == "number of output rows" and values.contains(metric.accumulatorId()):
                        total += int(values.apply(metric.accumulatorId()).replace(",", ""))
    return total


@pytest.mark.parametrize("copies", (30, 60))
def test_members_of_a_bucket_meet_its_hub_once_a_turn(spark, copies):
    """A group of near copies gives a row a member and bucket in each turn, not one more for each use of the join."""
    rng = random.Random(copies)
    base = [f"w{i}" for i in range(400)]
    rows = []
    for i in range(copies):
        words = list(base)
        for at in rng.sample(range(400), 3):
            words[at] = f"x{rng.random()}"
        rows.append((i, " ".join(words)))
    docs = spark.createDataFrame(rows, "doc_id long, text string")
    keys = minmax.signatures(docs).select("doc_id", F.explode("bands").alias("key")).distinct()
    members = keys.join(keys.groupBy("key").count().where("count > 1"), "key").count()
    since = spark._jsparkSession.sharedState().statusStore().executionsCount()
    got = minmax.link(docs)
    assert 0 < hub_rows(spark, since) <= members
    assert {r.component_id for r in got.collect()} == {0}


def test_near_duplicates_of_families_just_under_and_over_the_threshold(spark):
    """Chains of texts near 0.75, long and repeated texts, repeated and null ids: components as by brute force."""
    r = random.Random(16)
    rows, n = [], 0
    for _ in range(5):
        w = [f"v{r.randint(0, 9999)}" for _ in range(60)]
        for _ in range(30):
            rows.append((n, " ".join(w)))
            n += 1
            w = list(w)
            for _ in range(r.randint(1, 3)):
                w[r.randrange(60)] = f"z{r.randint(0, 99999)}"
    long = " ".join(f"q{i}" for i in range(30_000))
    rows += [(n, long), (n + 1, long + " end"), (n + 2, rows[3][1]), (n + 2, rows[45][1]), (n + 3, None), (n + 3, rows[100][1]), (None, rows[0][1]), (None, rows[0][1]), (n + 4, "")]
    got = minmax.near_duplicates(spark.createDataFrame(rows, "doc_id long, text string").repartition(5)).collect()
    assert len(got) == len(rows)
    s = minmax.Shingler()
    sets = [(i, set(s(t).tolist())) for i, t in rows if i is not None]
    label = {i: i for i, _ in sets}
    for x, (i, a) in enumerate(sets):
        for j, b in sets[:x]:
            if a and b and 100 * len(a & b) >= 75 * len(a | b) and label[i] != label[j]:
                lo, hi = sorted((label[i], label[j]))
                label = {k: lo if v == hi else v for k, v in label.items()}
    for x in got:
        if x["doc_id"] is None:
            assert x["component_id"] is None and x["kept"]
        elif x["n_shingles"]:
            assert (x["component_id"], x["kept"]) == (label[x["doc_id"]], label[x["doc_id"]] == x["doc_id"])
        else:
            assert x["component_id"] == x["doc_id"] and x["kept"]


def test_keep_one_of_repeated_and_null_ids(spark, odd):
    kept = minmax.keep_one(odd)
    assert kept.columns == odd.columns and sorted(r["doc_id"] for r in kept.where("doc_id is not null").collect()) == [0, 1, 2, 3, 4, 5, 7]
    assert kept.where("doc_id is null").count() == 1
    again = spark.createDataFrame([(1, "b c"), (1, "a b"), (1, "a b"), (2, "x"), (None, "n"), (None, "n")], "doc_id long, text string")
    assert sorted(map(str, (tuple(r) for r in minmax.keep_one(again).collect()))) == sorted(map(str, [(1, "a b"), (2, "x"), (None, "n"), (None, "n")]))
    assert minmax.near_duplicates(empty(spark)).count() == 0 and minmax.keep_one(empty(spark)).count() == 0


def test_top_k(spark):
    r = np.random.default_rng(1)
    v = r.normal(size=(300, 20)).round(2)
    v[7] = v[8]
    rows = [(i, x.tolist()) for i, x in enumerate(v)] + [(900, None), (901, [None] * 20), (902, [float("nan")] * 20)]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<double>")
    got = topk.search(df, df.where("vec_id % 50 = 0"), block=3).orderBy("query_id", "rank").collect()
    q = np.floor(256 * v).astype(np.int64)
    want = []
    for i in range(0, 300, 50):
        s = q @ q[i]
        order = [j for j in np.lexsort((np.arange(300), -s)) if j != i][:5]
        want += [(i, k + 1, j, s[j]) for k, j in enumerate(order)]
    assert [tuple(x) for x in got] == want


def test_url_intervals(spark):
    events = spark.createDataFrame([("a.com", 10, "add", "l"), ("a.com", 20, "remove", "l"), ("a.com", 30, "add", "l"), ("b.org/x", 5, "add", "l"), ("c.net", 5, "add", "l"), ("c.net", 5, "remove", "l")], "pattern string, day long, action string, list string")
    seen = [("http://w.a.com/1", 9, 0), ("http://w.a.com/1", 10, 1), ("http://a.com", 19, 1), ("http://a.com", 20, 0), ("https://a.com:8/", 31, 1), ("http://b.org/x?y", 6, 1), ("http://b.org/z", 6, 0), ("http://c.net/", 6, 0), (None, 6, 0), ("http://a.com", None, 0), ("http://a.com", 19, 1)]
    caps = spark.createDataFrame([(i, u, d) for i, (u, d, _) in enumerate(seen)], "page_id long, url string, fetch_day long")
    assert [int(r["blocked"]) for r in urls.judge(caps, events).orderBy("page_id").collect()] == [x[2] for x in seen]


def test_pipeline_keeps_and_drops(spark):
    import corpus_pipeline

    docs = spark.read.parquet(f"{SF}/documents.parquet")
    kept = docs
    for _, stage in corpus_pipeline.STAGES[:-1]:
        kept = stage(spark, kept, SF)
        assert kept.columns == docs.columns
    n = kept.count()
    assert 0.5 * docs.count() < n < docs.count()
    packed = corpus_pipeline.run(spark, SF)
    assert packed.select("doc_id").distinct().count() == n


def test_toxicity_fit_holds_the_words_of_one_text_at_a_time():
    import random
    import tracemalloc

    r = random.Random(3)
    rows = [(" ".join(r.choice("abcdefgh") * r.randrange(2, 9) for _ in range(400)), i % 2) for i in range(300)]
    tracemalloc.start()
    toxicity.Model(rows)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 3_000_000, peak  # 0.7 MB of text; 120 000 words of all texts take over 7 MB
