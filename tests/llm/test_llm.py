"""Training-data operators against brute-force versions, round trips and edge cases."""

import hashlib
import json
import random
import zlib
from collections import Counter, defaultdict

import numpy as np
import pytest
from pyspark.sql import functions as F

from farpoint.llm import ann, chat, components, jaccard, licenses, media, mixing, packing, tokens, toxicity, warc
from farpoint.llm.queries import tokenizer_path

DOCS = "doc_id long, text string, lang string, source string, n_chars long"


def docs(spark, rows):
    return spark.createDataFrame([(i, t, "en", s, len(t or "")) for i, t, s in rows], DOCS)


ODD = [(1, None, "a"), (2, "", "a"), (3, " \n\t", None), (4, "word", "b"), (4, "word", "b"), (None, "x y z", "b"), (6, "ñandú ﬁ 中文 🙂 İ Σς <|endoftext|> '\x00\x1f", "c"), (7, "long " * 60_000, "c")]


# 1 archives
def test_warc_round_trip(spark, tmp_path):
    big = "<p>" + "é" * 600
    rows = [(1, "http://a/ b", big), (2, None, big), (3, "u\n", big), (4, "x", "small"), (5, "x", "small"), (6, "n", None), (None, "q", big)]
    df = spark.createDataFrame(rows, "page_id long, url string, html string")
    folder, index = warc.write_archive(df, f"file://{tmp_path}/w")
    back = {r["record_id"]: r for r in warc.read_archive(spark, folder, index).collect()}
    assert len(back) == 7 and back["3"]["record_type"] == "response" and back["3"]["payload"] == big.encode()
    assert back["1"]["record_type"] == back["2"]["record_type"] == back["null"]["record_type"] == "revisit" and back["1"]["refers_to"] == "3"
    assert back["4"]["record_type"] == back["5"]["record_type"] == "response" and back["6"]["payload_bytes"] == 0
    assert back["2"]["payload_bytes"] == len(big.encode()) and back["2"]["payload_digest"] == hashlib.sha1(big.encode()).hexdigest()
    place = index.where("record_id = 3").first()
    head, http, payload = warc.read_record(folder, place["bundle"], place["offset"], place["size"])
    assert payload == big.encode() and head["warc-record-id"] == "<urn:record:3>"
    rows_folder, rows_index = warc.write_archive(df, f"file://{tmp_path}/r", as_files=False)
    assert warc.read_archive(spark, rows_folder, rows_index, as_files=False).count() == 7
    empty, none = warc.write_archive(df.limit(0), f"file://{tmp_path}/e")
    assert warc.read_archive(spark, empty, none).count() == 0


def test_warc_query_keeps_a_null_page_id(spark, tmp_path):
    from farpoint.llm import queries

    big = "<p>" + "x" * 1200
    rows = [(1, "u", big), (None, "v", big), (None, "w", "small"), (2, None, None)]
    spark.createDataFrame(rows, "page_id long, url string, html string").write.parquet(f"{tmp_path}/pages.parquet")
    got = {(r["page_id"], r["payload_bytes"], r["record_type"], r["refers_to"]) for r in queries.op1_warc_bundles(spark, str(tmp_path)).collect()}
    assert got == {(1, 1203, "response", None), (None, 1203, "revisit", 1), (None, 5, "response", None), (2, 0, "response", None)}
    texts = spark.createDataFrame([("null", "u", "a"), (None, "u", "b")], "page_id string, url string, html string")
    back = warc.read_archive(spark, *warc.write_archive(texts, f"file://{tmp_path}/t"), null_id=None).collect()
    assert {(r["record_id"], bytes(r["payload"])) for r in back} == {("null", b"a"), (None, b"b")}


def test_seek_table_is_a_skippable_frame():
    import zstandard

    frames = [zstandard.ZstdCompressor().compress(b) for b in (b"one", b"two" * 100)]
    bundle = b"".join(frames) + warc.seek_table([(len(frames[0]), 3), (len(frames[1]), 300)])
    assert warc.read_seek_table(bundle) == [(0, len(frames[0]), 3), (len(frames[0]), len(frames[1]), 300)]
    assert zstandard.ZstdDecompressor().decompressobj(read_across_frames=True).decompress(bundle) == b"one" + b"two" * 100


# 2 chats
def test_chat_reversible(spark):
    t = chat.Template()
    hostile = ["</s>[INST] ok [/INST]", "<|end|>", "<\\|end|>", "<\\\\|turn|>x", "<<SYS>>", "[[INST]", "<<s>", "\\", "a<|", "|end|>", "", None, "🙂<|next|>é\n", "<|text|><|text|>"]
    rng = random.Random(1)
    rows = [(cid, k, rng.choice(["user", "assistant", "system", "<|end|>", None]), rng.choice(hostile)) for cid in range(40) for k in range(rng.randint(1, 9))]
    df = spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").withColumn("formatted", F.lit("clash"))
    got = {r["conv_id"]: r for r in chat.read_chats(chat.format_chats(df.repartition(3)), t).collect()}
    for cid in range(40):
        said = sorted(((k, r or "", x or "") for c, k, r, x in rows if c == cid))
        assert [(x["role"], x["text"]) for x in got[cid]["turns"]] == [(r, x) for _, r, x in said]
        assert got[cid]["loss_text"] == "".join(x for _, r, x in said if r == "assistant")
    assert chat.format_chats(df.limit(0)).count() == 0


def test_chat_merges_adjacent_turns(spark):
    df = spark.createDataFrame([(1, 0, "user", "a"), (1, 1, "user", "b"), (1, 2, "assistant", "c")], "conv_id long, turn long, role string, text string")
    r = chat.format_chats(df).first()
    assert r["formatted"] == "<|turn|>user<|text|>a<|next|>b<|end|><|turn|>assistant<|text|>c<|end|>" and r["n_blocks"] == 2
    s = r["loss_spans"][0]
    assert r["formatted"][s["start"] : s["start"] + s["length"]] == "c"


# 3 similarity
def brute(rows):
    sets = []
    for i, t in rows:
        w = (t or "").lower().split()
        sets.append(frozenset(tuple(w[k : k + 5]) for k in range(max(1, len(w) - 4))) if w else frozenset())
    n, links = len(rows), Counter()
    root = list(range(n))

    def find(x):
        while root[x] != x:
            x = root[x]
        return x

    for a in range(n):
        for b in range(a):
            if sets[a] and sets[b] and len(sets[a] & sets[b]) >= 0.8 * len(sets[a] | sets[b]):
                links[a] += 1
                links[b] += 1
                root[max(find(a), find(b))] = min(find(a), find(b))
    group = defaultdict(list)
    for k in range(n):
        group[find(k)].append(k)
    least = {k: min((rows[m][0] for m in ms if rows[m][0] is not None), default=None) for ms in group.values() for k in ms}
    return sorted(((rows[k][0], least[k], links[k]) for k in range(n)), key=str)


@pytest.mark.parametrize("small", [256, 8])
def test_jaccard_against_brute_force(spark, monkeypatch, small):
    monkeypatch.setattr(jaccard, "SMALL", small)
    monkeypatch.setattr(jaccard, "BLOCK_TOKENS", 600 if small == 8 else 600_000)
    rng = random.Random(4)
    vocabulary = [f"w{k}" for k in range(400)]
    rows, base = [], [rng.choice(vocabulary) for _ in range(120)]
    for i in range(150):
        if i < 60:
            w = list(base)
            for _ in range(rng.randint(0, 3)):
                w[rng.randrange(len(w))] = rng.choice(vocabulary)
        else:
            w = [rng.choice(vocabulary) for _ in range(rng.randint(1, 90))]
        rows.append((i, " ".join(w)))
    rows += [(200, None), (201, ""), (202, rows[5][1]), (203, rows[5][1]), (203, rows[5][1]), (204, "one two"), (205, "One  TWO"), (206, "five words are just enough")]
    df = spark.createDataFrame(rows, "doc_id long, text string").withColumn("rid", F.lit(1)).withColumn("k1", F.lit("x"))
    got = sorted(((r["doc_id"], r["class_id"], r["n_links"]) for r in jaccard.similarity_classes(df).collect()), key=str)
    assert got == brute(rows)


@pytest.mark.parametrize("depth", [3, 6, 10])
def test_jaccard_recall_at_every_depth(depth):
    """Share of 400,000 ideal pairs at the threshold that no run finds when every bucket is split down to depth."""
    n, rng = 400_000, np.random.default_rng(6)
    equal = [np.packbits(rng.random(n) < jaccard.THRESHOLD) for _ in range(jaccard.SKETCH)]

    def below(run, node, level):
        if level == depth:
            return np.uint8(255)
        children = [jaccard.BRANCHES * node + b for b in range(jaccard.BRANCHES)]
        return np.bitwise_or.reduce([equal[jaccard._branch_order(run, c)] & below(run, c, level + 1) for c in children])

    runs = jaccard.runs_for(jaccard.RECALL)
    orders = [[jaccard._order(r, k) for k in range(jaccard.DEPTH)] for r in range(runs)]
    assert len({o for x in orders for o in x}) == runs * jaccard.DEPTH
    found = np.bitwise_or.reduce([np.bitwise_and.reduce([equal[o] for o in x]) & below(r, 1, jaccard.DEPTH) for r, x in enumerate(orders)])
    assert 1 - np.unpackbits(found)[:n].mean() <= 1 - jaccard.RECALL


def test_jaccard_pairs_in_a_hot_passage(spark):
    """Pairs near the threshold inside one very large group that shares a passage: buckets are split many times and no link may go."""
    rng = random.Random(8)
    passage = [f"p{k}" for k in range(60)]
    rows, pairs = [], 600
    for i in range(pairs):
        own = [f"o{i}x{k}" for k in range(60)]
        other = list(own)
        other[30] = "changed"  # 5 of 116 grams differ on this side
        other[50] = "again"
        rows += [(2 * i, " ".join(passage + own)), (2 * i + 1, " ".join(passage + other))]
    rng.shuffle(rows)
    got = jaccard.similarity_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert all(r["n_links"] == 1 and r["class_id"] == r["doc_id"] // 2 * 2 for r in got) and len(got) == 2 * pairs


def test_jaccard_exact_memory_is_bounded_by_tiles():
    """Many short sets in one block: counts and forest equal brute force, and no matrix of all rows is made."""
    import tracemalloc

    rng = np.random.default_rng(9)
    sets = [np.unique(np.concatenate([np.arange(16), 100 + rng.integers(0, 40, 5)])).astype(np.uint64) for _ in range(6000)]
    has = np.zeros((6000, 140), np.float32)
    for k, s in enumerate(sets):
        has[k, s.astype(int)] = 1
    size, rows, weight = has.sum(axis=1), np.arange(6000), rng.integers(1, 4, 6000).astype(float)
    tracemalloc.start()
    links, forest = jaccard.links_between(sets, rows, rows, weight)
    peak = tracemalloc.get_traced_memory()[1]
    tracemalloc.stop()
    assert peak < 150e6  # 6000 x 6000 in single precision alone is 144 MB
    common = has @ has.T
    hit = common >= 0.8 * (size[:, None] + size - common) - 1e-5
    np.fill_diagonal(hit, False)
    assert (links == hit @ weight).all() and all(hit[a, b] for a, b in forest)
    assert len(jaccard._dense_forest(hit, True)) == len(forest)
    half = jaccard.links_between(sets, rows[:2500], rows[2500:], weight)[0]
    assert (half[:2500] == hit[:2500, 2500:] @ weight[2500:]).all() and (half[2500:] == hit[2500:, :2500] @ weight[:2500]).all()


def test_jaccard_edges(spark):
    assert jaccard.similarity_classes(spark.createDataFrame([], "doc_id long, text string")).count() == 0
    kept = jaccard.keep_one(docs(spark, ODD))
    assert kept.columns == ["doc_id", "text", "lang", "source", "n_chars"]
    assert Counter(r["doc_id"] for r in kept.collect()) == Counter([1, 2, 3, 4, None, 6, 7])


def test_jaccard_many_rows_of_one_id(spark):
    """Null and repeated ids neither multiply nor mix texts."""
    base = " ".join(f"w{k}" for k in range(60))
    rows = [(None, f"{base} x{k % 40} y{k % 40}") for k in range(400)] + [(7, base), (7, base + " z"), (7, "other words altogether in this one")]
    got = jaccard.similarity_classes(spark.createDataFrame(rows, "doc_id long, text string")).collect()
    assert sorted(((r["doc_id"], r["class_id"], r["n_links"]) for r in got), key=str) == brute(rows)


def test_deep_blocks_meet_all_pairs(spark, monkeypatch):
    monkeypatch.setattr(jaccard, "DEEP_BLOCK", 10)
    large = spark.range(95).select(F.lit(1).cast("long").alias("path"), F.col("id").alias("rid"), F.lit(95).cast("long").alias("n"))
    by = defaultdict(set)
    for r in jaccard._block_pairs(large).collect():
        by[r["bucket"]].add(r["rid"])
    met = {(a, b) for g in by.values() for a in g for b in g if a < b}
    assert len(met) == 95 * 94 // 2 and max(map(len, by.values())) < 60


def test_components_of_hubs(spark):
    pairs = [(0, k) for k in range(1, 4000)] + [(9000 + k, 8999) for k in range(1, 2500)] + [(3999, 9001), (20_000, 20_001)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(pairs, "a long, b long").repartition(7)).collect()}
    assert set(got.values()) == {0, 20_000} and len(got) == 4000 + 2500 + 2


def test_clashing_names(spark):
    """Columns of any name survive the stages: none is lost, overwritten or mixed up with a helper."""
    names = ["_n", "n", "_row", "row", "doc", "copies", "_copies", "copy", "_id", "size", "hash", "pattern", "class_id", "k_n"]
    df = docs(spark, [(i, f"some words of text {i} here", "s") for i in range(20)]).select("*", *(F.concat(F.lit(f"{n}-"), F.col("doc_id")).alias(n) for n in names))
    for out in (jaccard.keep_one(df), mixing.mix_rows(df), toxicity.keep_clean(df, toxicity.ToxicityModel())):
        rows = out.collect()
        assert out.columns == df.columns and rows and all(r[n] == f"{n}-{r['doc_id']}" for r in rows for n in names)
    taken = ["_group", "group", "_level", "level", "_gap", "gap", "c0", "c1"]
    pieces = packing.cut(docs(spark, [(i, "w " * (i * 7), "s") for i in range(40)]), tokenizer_path("byte_bpe_50k.json"), None, capacity=64)
    pieces = pieces.select("*", *(F.concat(F.lit(f"{n}-"), F.col("doc_id")).alias(n) for n in taken), F.lit("old").alias("sequence_id"), F.lit("old").alias("offset"))
    out = packing.pack(pieces, capacity=64, group=16)
    rows = out.collect()
    assert out.columns == [c for c in pieces.columns if c not in ("sequence_id", "offset")] + ["sequence_id", "offset"]
    assert len(rows) == pieces.count() and all(r[n] == f"{n}-{r['doc_id']}" for r in rows for n in taken)


def test_components(spark):
    rng = random.Random(2)
    pairs = [(k, k + 1) for k in range(40)] + [(100 + rng.randrange(30), 100 + rng.randrange(30)) for _ in range(25)]
    got = {r["node"]: r["component"] for r in components.components(spark.createDataFrame(pairs, "a long, b long").repartition(5)).collect()}
    assert all(got[k] == 0 for k in range(41))
    assert all(got[a] == got[b] for a, b in pairs if a != b)
    assert components.components(spark.createDataFrame([(3, 3)], "a long, b long")).count() == 0


def test_plans_of_many_rounds_stay_small(spark, monkeypatch):
    """No plan of a round holds another round's or half's many times over, and levels of paths share their groupings: the driver keeps plans whole."""
    leaves = []

    def counted(df, name, stage=components.stage):
        leaves.append(df._jdf.queryExecution().optimizedPlan().collectLeaves().size())
        return stage(df, name)

    monkeypatch.setattr(components, "stage", counted)
    pairs = [(k, k + 1) for k in range(200)]
    got = components.components(spark.createDataFrame(pairs, "a long, b long").repartition(9)).collect()
    assert len(leaves) >= 3 and max(leaves) <= 12 and {r["component"] for r in got} == {0} and len(got) == 201

    monkeypatch.setattr(jaccard, "SMALL", 2)
    sketches = np.random.default_rng(3).integers(0, 2, (120, jaccard.SKETCH)).tolist()
    reps = jaccard.stage(spark.createDataFrame(list(enumerate(sketches)), "rid long, sketch array<int>"), "reps")
    levels = []
    monkeypatch.setattr(jaccard, "stage", lambda df, name, stage=jaccard.stage: (levels.append(name), stage(df, name))[1])
    plan = jaccard.candidate_edges(reps)._jdf.queryExecution().optimizedPlan().toString()
    assert sum(n.startswith("pivots") for n in levels) >= 2 and plan.count("Aggregate [") <= 4


# 4 mixing
def test_targets():
    goal = mixing.targets({"a": 100, "b": 100, None: 100})
    assert sum(goal.values()) == pytest.approx(450) and goal["a"] == 200 and goal["b"] < goal[None] <= 200
    assert mixing.targets({"a": 0}) == {"a": 0.0} and mixing.targets({}) == {}


def test_flow_prefers_unused_words():
    p = mixing.plan({("a",): 10, ("a", "b"): 10}, {"a": 10.0, "b": 10.0})
    assert p.words == {("a",): 10, ("a", "b"): 10} and p.routed[(("a", "b"), "b")] == 10
    p = mixing.plan({("a",): 10}, {"a": 15.0})
    assert p.words[("a",)] == 15


def shortest_paths(patterns, goal, passes=2):
    """(words moved, cost) of a min-cost maximal flow, one unit path after another by Bellman-Ford."""
    names, sources = list(patterns), list(goal)
    edges = []  # from, to, room, cost

    def edge(a, b, room, cost):
        edges.extend([[a, b, room, cost], [b, a, 0, -cost]])

    for p in names:
        for k in range(passes):
            edge("from", p, patterns[p], k * k)
        for s in p:
            edge(p, ("s", s), 10**9, 0)
    for s in sources:
        edge(("s", s), "to", goal[s], 0)
    moved = cost = 0
    while True:
        far, came = {"from": 0}, {}
        for _ in range(len(names) + len(sources) + 2):
            for k, (a, b, room, c) in enumerate(edges):
                if room > 0 and a in far and far[a] + c < far.get(b, 10**9):
                    far[b], came[b] = far[a] + c, k
        if "to" not in far:
            return moved, cost
        at = "to"
        push = 10**9
        while at != "from":
            push, at = min(push, edges[came[at]][2]), edges[came[at]][0]
        at = "to"
        while at != "from":
            k = came[at]
            edges[k][2] -= push
            edges[k ^ 1][2] += push
            at = edges[k][0]
        moved, cost = moved + push, cost + push * far["to"]


def test_flow_against_shortest_paths():
    rng = random.Random(31)
    for _ in range(60):
        names = "abcde"[: rng.randint(1, 5)]
        patterns = {tuple(sorted(rng.sample(names, rng.randint(1, len(names))))): rng.randint(1, 30) for _ in range(rng.randint(1, 9))}
        goal = {s: rng.randint(0, 40) for s in names}
        p = mixing.plan(patterns, goal)
        words, cost = shortest_paths(patterns, goal)
        assert sum(p.words.values()) == pytest.approx(words, abs=1e-3)
        assert sum(max(0.0, n - patterns[q]) for q, n in p.words.items()) == pytest.approx(cost, abs=1e-3)
        for q, n in p.words.items():
            assert n <= 2 * patterns[q] + 1e-6 and sum(v for (r, _), v in p.routed.items() if r == q) == pytest.approx(n, abs=1e-3)
        for s, g in goal.items():
            assert sum(v for (_, t), v in p.routed.items() if t == s) <= g + 1e-3


def test_flow_of_many_patterns_is_fast():
    import time

    rng = random.Random(32)
    names = [f"s{k:02}" for k in range(20)]
    patterns = {}
    while len(patterns) < 100_000:
        patterns[tuple(sorted(rng.sample(names, rng.randint(1, 8))))] = rng.randint(100, 9000)
    sizes = Counter()
    for p, n in patterns.items():
        for s in p:
            sizes[s] += n
    total = sum(patterns.values())
    goal = {s: 1.2 * total * (k + 1) / 210 for k, s in enumerate(names)}
    began = time.perf_counter()
    p = mixing.plan(patterns, goal)
    assert time.perf_counter() - began < 60
    got = Counter()
    for (_, s), v in p.routed.items():
        got[s] += v
    assert all(abs(got[s] - g) < 1 for s, g in goal.items()) and all(n <= 2 * patterns[q] + 1e-3 for q, n in p.words.items())


def test_mix(spark):
    rng = random.Random(3)
    rows = [(1000 + i, " ".join(["w"] * rng.randint(0, 50)), rng.choice(["s1", "s2", "s2", "s2", None])) for i in range(800)] + ODD
    taken, by_source = mixing.mix(docs(spark, rows), F.array("source"), carry=("source",))
    got = taken.collect()
    assert len(got) == len(rows)
    want = {r["s_source"]: r["target"] for r in by_source.collect()}
    total = Counter()
    for r in got:
        assert 0 <= r["taken"] <= 2 * r["size"]
        total[r["source"]] += r["taken"]
    assert all(abs(total[s] - t) <= 1 for s, t in want.items())
    again, _ = mixing.mix(docs(spark, rows[::-1]).repartition(3), F.array("source"), carry=("source",))
    assert Counter(map(tuple, again.collect())) == Counter(map(tuple, got))
    none, _ = mixing.mix(docs(spark, rows).limit(0), F.array("source"))
    assert none.count() == 0
    mixed = mixing.mix_rows(docs(spark, rows))
    assert mixed.columns == ["doc_id", "text", "lang", "source", "n_chars"] and max(Counter(r["doc_id"] for r in mixed.where("doc_id >= 1000").collect()).values()) <= 2


def test_overlapping_members(spark):
    df = spark.createDataFrame([(i, "a b c d", ["x"] if i % 2 else ["y", "x"]) for i in range(100)], "doc_id long, text string, m array<string>")
    taken, by_source = mixing.mix(df, F.col("m"))
    assert {r["s_source"]: r["source_size"] for r in by_source.collect()} == {"x": 400, "y": 200}
    # Targets are 300 and 200 of 600 and 400 words' weights: x takes its own documents once before anything is repeated.
    got, want = taken.collect(), {r["s_source"]: r["target"] for r in by_source.collect()}
    assert want == mixing.targets({"x": 400, "y": 200}) and all(r["taken"] <= 2 * r["size"] for r in got)
    p = mixing.plan({("x",): 200, ("x", "y"): 200}, want)
    assert sum(r["taken"] for r in got) == pytest.approx(sum(p.words.values()), abs=2) == min(800, sum(want.values()))
    routed = Counter()
    for (_, source), n in p.routed.items():
        routed[source] += n
    assert sum(routed.values()) == pytest.approx(min(800, sum(want.values()))) and all(routed[k] <= want[k] + 1e-6 for k in want)
    own = Counter()
    for r in got:
        own[r["pattern"]] += r["taken"]
    assert sorted(own.values()) == sorted(int(round(n)) for n in p.words.values())


# 5 toxicity
def test_grammar_weights_clauses():
    m = toxicity.ToxicityModel()
    w = lambda t: sum(x for _, x in m.clauses(t))
    assert w("you are an idiot") > w("an idiot") > w("not an idiot") > 0
    assert w("you are an idiot") > w("they said you are an idiot")
    assert w("we will kill you") > w("kill the process") and w("the weather is fine") == 0
    # Reported speech goes on across colons, commas and quotes; curly apostrophes negate too; a pause ends a negation.
    assert w("he said: you are an idiot") < w("you are an idiot") > w("she wrote, \u201cyou are an idiot\u201d") > 0
    assert w("I don\u2019t say idiot") == w("I don't say idiot") < w("I do say idiot") == w("not that, idiot")
    assert m.score(None) == m.score("") == m.score("plain words only") < 0.5 < m.score("you stupid worthless idiot. you moron.")


def test_toxicity_learns_words_and_holds_out(spark):
    rng = random.Random(5)
    rows, marks = [], []
    for i in range(600):
        toxic = i % 4 == 0
        w = [rng.choice(["lorem", "ipsum", "dolor", "sit", "amet", "elit"]) for _ in range(20)]
        if toxic:
            w[rng.randrange(20)] = "grbl" + rng.choice(["ak", "on", "ix"])
        rows.append((i, " ".join(w), "s"))
        marks.append((i, int(toxic)))
    labels = spark.createDataFrame(marks, "doc_id long, toxic int")
    model = toxicity.fit(docs(spark, rows), labels)
    got = {r["doc_id"]: r["score"] for r in toxicity.score(docs(spark, rows + ODD), model).collect()}
    held = [i for i, _ in marks if zlib.crc32(str(i).encode()) % 5 == 0]
    assert np.mean([(got[i] >= 0.5) == (i % 4 == 0) for i in held]) > 0.97
    kept = toxicity.keep_clean(docs(spark, rows + ODD), model)
    assert kept.columns == ["doc_id", "text", "lang", "source", "n_chars"] and {r["doc_id"] for r in kept.collect()} >= {1, 2, 3, 4, 6, 7}
    long = "q" * 70  # words of any length are learned
    more = [(1000 + i, f"amet {long} elit" if i % 4 == 0 else "amet elit", "s") for i in range(400)]
    assert long in toxicity.fit(docs(spark, more), spark.createDataFrame([(1000 + i, int(i % 4 == 0)) for i in range(400)], "doc_id long, toxic int")).words
    assert toxicity.fit(docs(spark, rows), labels.limit(0)).words == {} and toxicity.score(docs(spark, rows).limit(0), model).count() == 0


def _speech(rng, n):
    """Texts with the same insult words in both classes: what tells them apart is negation, report and target."""
    rows, marks = [], []
    for i in range(n):
        word = rng.choice(toxicity.INSULTS[:18])
        filler = " ".join(rng.choice(["lorem", "ipsum", "dolor", "amet", "elit", "quam"]) for _ in range(rng.randint(3, 12)))
        toxic = i % 3 == 0
        said = rng.choice([f"you are a {word}", f"{word}, you", f"you {word}", f"she is a {word}"]) if toxic else rng.choice([f"you are not a {word}", f"she said: you are a {word}", f"you are never a {word}", f"they wrote, you {word}"])
        rows.append((i, f"{filler}. {said}. {filler}", "s"))
        marks.append((i, int(toxic)))
    return rows, marks


def test_grammar_is_worth_its_arcs(spark, monkeypatch):
    """Held-out accuracy with the learned machine and with one that only adds words up."""
    rows, marks = _speech(random.Random(12), 1500)
    labels, df = spark.createDataFrame(marks, "doc_id long, toxic int"), docs(spark, rows)
    held = [i for i, _ in marks if zlib.crc32(str(i).encode()) % 5 == 0]

    def accuracy():
        model = toxicity.fit(df, labels)
        score = {i: model.score(t) for i, t, _ in rows}
        return np.mean([(score[i] >= 0.5) == (i % 3 == 0) for i in held]), model

    whole, model = accuracy()
    assert model.arcs != toxicity.Arcs() and model.arcs.negated <= toxicity.Arcs().negated
    monkeypatch.setattr(toxicity.Arcs, "others", lambda self: [])
    monkeypatch.setattr(toxicity, "grammar", lambda arcs=None, made=toxicity.grammar: made(toxicity.FLAT))
    flat, _ = accuracy()
    assert whole > 0.95 and whole > flat + 0.1


def brute_clauses(model, text):
    """Weights of the matched clauses by scanning words left to right, without any machine."""
    out = []
    for clause in toxicity._CLAUSE.split((text or "").lower().replace("\u2019", "'")):
        words = toxicity._TOKEN.findall(clause)
        kind = ["pause" if w in ",:" else model.symbol.get(w) or ("insult" if w[:4] in model.beginnings else "other") for w in words]
        if not {"insult", "threat"} & set(kind):
            continue
        total, arcs = 0.0, model.arcs
        for k, s in enumerate(kind):
            spoken = [j for j in range(k) if kind[j] != "pause"]
            if s == "target":
                near = [kind[j] for j in spoken[-4:]]
                last = max((j for j, q in enumerate(near) if q in ("insult", "threat")), default=None)
                total += arcs.followed if last is not None and "target" not in near[last:] else 0.0
            if s in ("insult", "threat"):
                weight = 1.0 if s == "insult" else arcs.threat
                before = kind[max((j + 1 for j in range(k) if kind[j] == "pause"), default=0) : k]
                weight *= arcs.negated if "negation" in before[-3:] else 1
                weight *= arcs.reported if "report" in kind[:k] else 1
                weight *= arcs.targeted if "target" in [kind[j] for j in spoken[-4:]] else 1
                total += weight
        sure = max([model.words.get(w) or model.beginnings.get(w[:4]) or 1.0 for w, s in zip(words, kind) if s == "insult"], default=1.0)
        out.append(total * sure)
    return out


def test_machine_against_a_scan():
    rng = random.Random(21)
    model = toxicity.ToxicityModel({"grob": 1.4}, {"blar": 0.8}, arcs=toxicity.Arcs(0.7, 0.2, 0.5, 1.75, 0.3))
    pool = ["idiot", "kill", "you", "not", "said", ",", ":", "x", "grob", "blarney", "y", "z", "."]
    for _ in range(3000):
        text = " ".join(rng.choices(pool, k=rng.randint(1, 25)))
        assert np.allclose([w for _, w in model.clauses(text)], brute_clauses(model, text))


# 6 packing
def test_packing(spark):
    from tokenizers import Tokenizer

    path = tokenizer_path("byte_bpe_50k.json")
    rng = random.Random(6)
    rows = [(i, " ".join(rng.choice(["alpha", "beta", "gamma\n", "été", "42"]) for _ in range(rng.randint(0, 900))), "s") for i in range(300)] + ODD
    placed = packing.pack(packing.cut(docs(spark, rows), path, tokenizer_path("byte_bpe_50k.tiktoken"), capacity=512), capacity=512, group=64)
    got = placed.collect()
    library = Tokenizer.from_file(path)
    want = Counter()
    for i, t, _ in rows:
        ids = np.array([*library.encode(t or "", add_special_tokens=False).ids, 0], "<u4")
        first = len(ids) % 512 or 512
        for k, a in enumerate([0, *range(first, len(ids), 512)]):
            z = first if k == 0 else a + 512
            want[(i, k, a, z - a, zlib.crc32(ids[a:z].tobytes()))] += 1
    assert Counter((r["doc_id"], r["piece"], r["start"], r["length"], r["ids_crc32"]) for r in got) == want
    by = defaultdict(list)
    for r in got:
        by[r["sequence_id"]].append((r["offset"], r["length"]))
    for parts in by.values():
        at = 0
        for o, n in sorted(parts):
            assert o == at
            at += n
        assert at <= 512
    assert len(by) <= 1.03 * -(-sum(r["length"] for r in got) // 512) + 1
    assert packing.pack(packing.cut(docs(spark, rows).limit(0), path, None)).count() == 0


def test_sum_of_squares_choice():
    seq, off, gap = packing.sum_of_squares(np.array([6, 6, 4, 4]), 10)
    assert seq.tolist() == [0, 1, 1, 0] and off.tolist() == [0, 0, 6, 6] and gap.tolist() == [0, 0, 0, 0]


# 7 media
def test_formats_round_trip():
    rng = np.random.default_rng(1)
    g, c = rng.integers(0, 256, (7, 5), dtype=np.uint8), rng.integers(0, 256, (6, 9, 3), dtype=np.uint8)
    assert (media.decode(media.encode_pgm(g)) == g).all() and (media.decode(media.encode_ppm(c)) == c).all() and (media.decode(media.encode_bmp(c)) == c).all()
    assert (media.decode(b"P2\n2 1\n15\n0 15\n") == [[0, 255]]).all() and (media.decode(b"P5 2 1 100\n\x00\x32") == [[0, 128]]).all()
    assert (media.decode(b"P1\n3 2\n1 0 1\n# x\n011") == [[0, 255, 0], [255, 0, 0]]).all() and (media.decode(b"P4 10 1\n\xa0\x40") == [[0, 255, 0, 255, 255, 255, 255, 255, 255, 0]]).all()
    pam = b"P7\nWIDTH 2\nHEIGHT 1\nDEPTH 4\nMAXVAL 255\nTUPLTYPE RGB_ALPHA\nENDHDR\n" + bytes(range(8))
    assert media.decode(pam).tolist() == [[[0, 1, 2], [4, 5, 6]]]
    deep = rng.integers(0, 65536, (3, 4)).astype(">u2")
    assert (media.decode(b"P5 4 3 65535\n" + deep.tobytes()) == deep).all()
    import struct

    short = struct.pack("<2sIHHI", b"BM", 0, 0, 0, 54 + 8) + struct.pack("<IiiHHIIiiII", 40, 4, 1, 1, 8, 0, 4, 0, 0, 2, 0) + bytes(8) + bytes([0, 1, 2, 0])
    for bad in (short, b"P5 9 9 255\n123", b"P5 2 1 70000\nxx", b"P2 2 1 7\n9 9", b"P7\nWIDTH 2\n", b"BM", b"P6 0", b"P5 2 1 0\n\0\0"):
        with pytest.raises((ValueError, struct.error)):
            media.decode(bad)
    assert (media.decode(b"P2 # note\n2 2\n255\n1 2\n3 4\n") == [[1, 2], [3, 4]]).all()


def test_area_resize_matches_averages():
    rng = np.random.default_rng(2)
    x = rng.integers(0, 256, (12, 18), dtype=np.uint8)
    assert np.allclose(media.area_resize(x, 4, 6), x.reshape(4, 3, 6, 3).mean((1, 3)))
    fine = np.repeat(np.repeat(x.astype(float), 5, 0), 7, 1)  # 60 x 126
    assert np.allclose(media.area_resize(x, 5, 7), fine.reshape(5, 12, 7, 18).mean((1, 3)))
    assert np.load(__import__("io").BytesIO(media.tile(x))).shape == (16, 16) and len(media.difference_hash(x)) == 16


def test_text_media(spark):
    got = media.text_media(docs(spark, ODD), keep=True).collect()
    assert len(got) == len(ODD)
    for r, (i, t, _) in zip(got, ODD):
        n, payload = media.text_payload(t)
        assert (r["n_bytes"], r["payload_bytes"], r["payload_sha256"]) == (n, len(payload), hashlib.sha256(payload).hexdigest())
        assert r["tail_crc32"] == zlib.crc32(payload[-64:]) and media.decode(r["media"]).tobytes() == payload and r["media_sha256"] == hashlib.sha256(r["media"]).hexdigest()
    images = spark.createDataFrame([(1, bytearray(media.encode_bmp(np.zeros((3, 3, 3), np.uint8)))), (2, bytearray(b"no")), (3, None), (4, bytearray(b"P5 9 9 255\n1")), (5, bytearray(b"P5 2 1 65535\n\xff\xff\x00\x00"))], "id long, data binary")
    assert [r["height"] for r in media.image_columns(images, "id", "data").collect()] == [3, None, None, None, 1]
    assert media.text_media(docs(spark, ODD).limit(0)).count() == 0 and np.load(__import__("io").BytesIO(got[3]["tile"])).shape == (16, 16)


# 8 vectors
def test_search_recall_and_ties(spark):
    rng = np.random.default_rng(8)
    x = rng.standard_normal((1500, 16)).astype(np.float32)
    x[300:800] = x[300]  # one hot vector
    rows = [(i, v.tolist()) for i, v in enumerate(x)] + [(5000, None), (5001, [0.0] * 16), (5002, [float("nan")] * 16), (5003, [None] * 16), (5004, [1.0]), (10, x[10].tolist())]
    df = spark.createDataFrame(rows, "vec_id long, embedding array<float>")
    key = lambda d: {(r["query_id"], r["rank"]): (r["vec_id"], r["score"]) for r in d.collect()}
    got, want = key(ann.search(df, F.col("vec_id") % 50 == 0)), key(ann.exact_search(df.where(F.size("embedding") == 16), F.col("vec_id") % 50 == 0))
    queries = {q for q, _ in want}
    assert {q for q, _ in got} == queries and len(queries) == 30
    hits = sum(len({got[q, r][0] for r in range(1, 11)} & {want[q, r][0] for r in range(1, 11)}) for q in queries)
    assert hits >= 0.9 * 10 * len(queries)
    assert [got[350, r][0] for r in range(1, 11)] == list(range(300, 310))
    assert ann.search(df.limit(0), F.lit(True)).count() == 0
    assert ann.search(df.where("vec_id < 3"), F.lit(True)).groupBy("query_id").count().first()["count"] == 2


def test_large_parts_are_dealt_into_slots(spark, monkeypatch):
    monkeypatch.setattr(ann, "SLOT", 60)
    rng = np.random.default_rng(18)
    df = spark.createDataFrame([(i, v.tolist()) for i, v in enumerate(rng.standard_normal((1200, 8)))], "vec_id long, embedding array<double>")
    key = lambda d: {(r["query_id"], r["rank"]): r["vec_id"] for r in d.collect()}
    dealt = key(ann.search(df, F.col("vec_id") % 100 == 0))
    monkeypatch.setattr(ann, "SLOT", 10**9)
    assert dealt == key(ann.search(df, F.col("vec_id") % 100 == 0)) and len(dealt) == 120


def test_parts_are_balanced():
    x = np.random.default_rng(9).standard_normal((700, 8)).astype(np.float32)
    part = ann.balanced_parts(x, ann.neighbour_graph(x, 5), 3)
    assert set(np.bincount(part)) <= {87, 88}


# 9 tokens
def test_token_counts(spark):
    from tokenizers import Tokenizer

    path = tokenizer_path("word_bpe_49k.json")
    library = Tokenizer.from_file(path)
    texts = [(i, t) for i, t, _ in ODD] + [(20, "It's 3½ of ÉCOLE_x--'ll don't!! ΑΣ"), (21, "<|startoftext|>hi"), (22, "tab\tnew\nline\rx y"), (23, "ﬀ ² ª º ǅ İ"), (24, "a_b __ --- ‘’“” …")]
    got = tokens.count_tokens(spark.createDataFrame(texts, "doc_id long, text string"), path).collect()
    for r, (_, t) in zip(got, texts):
        n = len(library.encode(t or "", add_special_tokens=False).ids)
        assert (r["n_tokens"], r["n_bytes"], r["over_limit"]) == (n, len((t or "").encode()), n > 2048)


def test_shortcut_is_proved_and_agrees(sf):
    import pyarrow.parquet as pq

    counter = tokens.word_counter(tokenizer_path("word_bpe_49k.json"))
    assert len(counter.proved) > 10_000
    texts = pq.read_table(f"{sf}/documents.parquet")["text"].to_pylist()
    assert counter.count(texts) == [len(e.ids) for e in counter.library.encode_batch(texts, add_special_tokens=False)]
    enc = tokens.byte_encoder(tokenizer_path("byte_bpe_50k.json"), tokenizer_path("byte_bpe_50k.tiktoken"))
    assert all(enc.ids(t) == enc.library.encode(t, add_special_tokens=False).ids for t in texts + [t or "" for _, t, _ in ODD])


def test_empty_tables_give_empty_results(spark):
    none = docs(spark, []).limit(0)
    assert tokens.count_tokens(none, tokenizer_path("word_bpe_49k.json")).count() == 0 and licenses.scan_licenses(none).count() == 0


# 10 licences
def test_license_words_and_places(spark):
    import re

    texts = [(i, t) for i, t, _ in ODD] + [(30, "The MIT License. CC-BY, gnu General\nPublic LICENSE; Apache license mit-license"), (31, "mit license mit license"), (32, "amit license"), (33, "cc byé cc by é")]
    got = licenses.scan_licenses(spark.createDataFrame(texts, "doc_id long, text string")).collect()
    for r, (_, t) in zip(got, texts):
        low = re.sub("[A-Z]", lambda m: m[0].lower(), t or "")
        words = re.findall(r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+", low)
        places = [(k, label) for p, label in licenses.BASE.items() for k in range(len(words)) if words[k : k + len(p.split())] == p.split()]
        at = [k for k, _ in places]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"]) == (len(words), len(at), min(at, default=None), max(at, default=None))
        assert r["base_labels"] == ",".join(sorted({x for _, x in places})) and set(filter(None, r["base_labels"].split(","))) <= set(r["labels"].split(","))
        assert 0 <= r["score"] <= 1


def test_expressions():
    alt = lambda t: {"&".join(sorted(a)) for a in licenses.parse_expression(t).alternatives()}
    assert alt("MIT OR Apache-2.0 AND BSD-3-Clause") == {"mit", "apache-2.0&bsd-3-clause"}
    assert alt("(MIT OR Apache-2.0) AND ISC") == {"isc&mit", "apache-2.0&isc"}
    assert alt("GPL-2.0-only WITH Classpath-exception-2.0 OR MIT */") == {"gpl-2.0-only with classpath-exception-2.0", "mit"}
    assert alt("MIT OR") == {"mit"} and alt("(MIT") == {"mit"} and licenses.parse_expression("AND") is None and licenses.parse_expression("") is None
    for n in (8, 9, 40):  # long conjunctions keep their meaning
        c = licenses.parse_expression(" AND ".join(f"(a{k}-1 OR b{k}-1)" for k in range(n)))
        assert c.allows({f"a{k}-1" for k in range(n)}) and not c.allows({f"a{k}-1" for k in range(n - 1)}) and len(c.licences) == 2 * n
        if n == 8:
            assert len(set(c.alternatives())) == 256
    assert licenses.parse_expression("(MIT OR ISC) AND (ISC OR MIT) WITH x-1").text() == "(isc with x-1|mit with x-1)&(isc|mit)"
    for word in ("see the file", "NONE", "NOASSERTION", "the MIT"):
        assert licenses.parse_expression(word) is None
    assert licenses.scan("SPDX-License-Identifier: see the file").labels == [] and licenses.scan("SPDX-License-Identifier: NONE").labels == []
    assert licenses.scan("SPDX-License-Identifier: LicenseRef-Mine OR BSD-2-Clause").labels == ["bsd-2-clause", "licenseref-mine"]
    s = licenses.scan("// SPDX-License-Identifier: (MIT OR Apache-2.0)\ncode")
    assert {"mit", "apache-2.0"} <= set(s.labels) and s.score == 1.0


# pipeline
def test_pipeline_stages(spark, sf):
    import corpus_pipeline as cp

    d = spark.read.parquet(f"{sf}/documents.parquet")
    for name, step in cp.STAGES[:-1]:
        out = step(spark, d, sf)
        assert out.columns == d.columns
        d = spark.createDataFrame(out.toPandas(), out.schema)
        if name == "ngram_jaccard":
            got = [(r["doc_id"], r["text"]) for r in d.collect()]
            assert all(n == 0 for _, _, n in brute(got))
    packed = cp.STAGES[-1][1](spark, d, sf).toPandas()
    assert packed.groupby("sequence_id")["length"].sum().max() <= 2048 and set(packed["doc_id"]) == {r["doc_id"] for r in d.select("doc_id").collect()}
    for _, step in cp.STAGES:
        step(spark, d.limit(0), sf).collect()


def test_registered_queries_on_a_whole_table(spark, sf):
    """Every registered query against brute force on all documents of the smallest tables."""
    from tokenizers import Tokenizer

    import __spark_entry__ as e

    q = {n.split("_")[0]: f for n, f in e.queries().items() if n.startswith("op")}
    rows = [tuple(r) for r in spark.read.parquet(f"{sf}/documents.parquet").select("doc_id", "text", "source").collect()]
    text = {i: t or "" for i, t, _ in rows}
    got = sorted(((r["doc_id"], r["class_id"], r["n_links"]) for r in q["op3"](spark, sf).collect()), key=str)
    assert got == brute([(i, t) for i, t, _ in rows])
    size = {i: len(__import__("re").findall(r"[^\x20\x09-\x0D]+", t)) for i, t in text.items()}
    total = Counter()
    for i, _, s in rows:
        total[s] += size[i]
    goal, by = mixing.targets(total), Counter()
    mixed = q["op4"](spark, sf).collect()
    source = {i: s for i, _, s in rows}
    for r in mixed:
        assert r["size"] == size[r["doc_id"]] and r["source_size"] == total[source[r["doc_id"]]] and r["target"] == pytest.approx(goal[source[r["doc_id"]]]) and 0 <= r["taken"] <= 2 * r["size"]
        by[source[r["doc_id"]]] += r["taken"]
    assert len(mixed) == len(rows) and all(abs(by[s] - g) <= 1 for s, g in goal.items())
    scored = q["op5"](spark, sf).collect()
    assert len(scored) == len(rows) and all(r["held_out"] == (zlib.crc32(str(r["doc_id"]).encode()) % 5 == 0) and r["predicted"] == (r["score"] >= 0.5) and 0 <= r["score"] <= 1 for r in scored)
    again = {r["doc_id"]: r["score"] for r in q["op5"](spark, sf).collect()}
    assert all(again[r["doc_id"]] == pytest.approx(r["score"]) for r in scored)
    library, ends = Tokenizer.from_file(tokenizer_path("byte_bpe_50k.json")), defaultdict(int)
    pieces = q["op6"](spark, sf).collect()
    ids = {i: np.array([*library.encode(t, add_special_tokens=False).ids, 0], "<u4") for i, t in text.items()}
    for r in sorted(pieces, key=lambda r: (r["sequence_id"], r["offset"])):
        assert r["offset"] == ends[r["sequence_id"]] and r["ids_crc32"] == zlib.crc32(ids[r["doc_id"]][r["start"] : r["start"] + r["length"]].tobytes())
        ends[r["sequence_id"]] += r["length"]
    assert max(ends.values()) <= 2048 and sum(ends.values()) == sum(map(len, ids.values()))
    for r in q["op7"](spark, sf).collect():
        n, payload = media.text_payload(text[r["doc_id"]])
        assert (r["n_bytes"], r["payload_sha256"], r["tail_crc32"]) == (n, hashlib.sha256(payload).hexdigest(), zlib.crc32(payload[-64:]))
    x = {r["vec_id"]: np.array(r["embedding"], float) for r in spark.read.parquet(f"{sf}/embeddings.parquet").select("vec_id", "embedding").collect()}
    near = defaultdict(list)
    for r in q["op8"](spark, sf).orderBy("query_id", "rank").collect():
        near[r["query_id"]].append(r["vec_id"])
        assert r["score"] == pytest.approx(float(np.sqrt(((x[r["query_id"]] - x[r["vec_id"]]) ** 2).sum())), rel=1e-14)
    want = {i: sorted((float(np.sqrt(((x[i] - v) ** 2).sum())), j) for j, v in x.items() if j != i)[:10] for i in x if i % 100 == 0}
    assert set(near) == set(want) and sum(len(set(near[i]) & {j for _, j in w}) for i, w in want.items()) >= 9 * len(want)
    word = Tokenizer.from_file(tokenizer_path("word_bpe_49k.json"))
    assert all(r["n_tokens"] == len(word.encode(text[r["doc_id"]], add_special_tokens=False).ids) for r in q["op9"](spark, sf).collect())
    for r in q["op10"](spark, sf).collect():
        words = licenses.words_of(text[r["doc_id"]])
        at = [k for p in licenses.BASE for k in range(len(words)) if words[k : k + len(p.split())] == p.encode().split()]
        assert (r["n_words"], r["n_base"], r["first_word"], r["last_word"]) == (len(words), len(at), min(at, default=None), max(at, default=None))


def test_queries_registered():
    import __spark_entry__ as e

    names = set(e.queries())
    assert all(any(n.startswith(f"op{k}_") for n in names) for k in range(1, 11)) and "pipeline" in names
    assert json.dumps(sorted(e.oracle_sql()))
