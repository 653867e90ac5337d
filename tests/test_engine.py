import pytest
from pyspark.sql import functions as F

from winsub.kernel.window_index import WindowIndex
from winsub.operators import features, measures
from winsub.operators.features import count_grams, qgram_features, signature
from winsub.operators.locate import METHODS, count_matches, locate, locate_array
from winsub.operators.replay import replay_tails
from winsub.operators.segments import expire_segments, locate_segmented, read_index, seal_segments, write_index
from winsub.operators.staging import drop_staged, shared_folder, staged
from winsub.operators.suffix import tree_nodes
from winsub.operators.tail import leaf_hits, tail_case_split, tail_hits, tail_table
from winsub.operators.windows import make_queries, sample_queries, window_at
from winsub.plans import planner
from winsub.sources.adapters import FAMILIES, assemble, chunks, encode_symbols, family, family_symbols, family_window, numbered, symbol_chunks, symbols, texts
from winsub.sources.readers import load, load_text, register_source, symbol_rate
from winsub.sources.sinks import save_parquet, to_memory, upsert_batches
from winsub.streaming.live import LiveWindow, counts, live_locate, near_events, once, reordered, state_store

ODD = [("a", "a%_b'\"\n\\E.*(?=ü)𝒳ü𝒳"), ("b", ""), ("c", None), (None, "x"), ("d", "ab" * 40), ("e", "x")]


def rows(df):
    return sorted(map(tuple, df.collect()))


@pytest.fixture(scope="module")
def odd(spark):
    return window_at(texts(spark.createDataFrame(ODD, "k string, t string"), "k", "t"), 60)


def truth(patterns, capacity=60):
    out = []
    for k, t in ODD:
        if k is None or not t:
            continue
        w, start = t[-capacity:], max(0, len(t) - capacity)
        out += [(k, p, len(t), start + i) for p in patterns for i in range(len(w) - len(p) + 1) if w[i : i + len(p)] == p]
    return sorted(out)


@pytest.mark.parametrize("method", METHODS)
def test_methods_on_odd_texts(spark, odd, method):
    patterns = ["%", "_", "'", '"', "\n", "\\E", ".*", "(?=", "ü", "𝒳", "𝒳ü", "abab", "ba", "ab" * 40, "zz"]
    assert rows(locate(odd, make_queries(spark, patterns), method=method)) == truth(patterns)


def test_keyed_many_and_refused_queries(spark, odd, monkeypatch):
    q = spark.createDataFrame([("1", "d", "ba", None), ("2", "a", "ba", None), ("3", "d", None, None)], "query_id string, stream_id string, pattern string, at_seq bigint")
    assert {r[3] for r in rows(locate(odd, q, method="index"))} == {r[3] for r in truth(["ba"]) if r[0] == "d"}
    monkeypatch.setattr(planner, "SENT_QUERIES", 1)  # too many to send: an equi-join on q-grams
    patterns = ["ab", "ü", "ababababab"]
    assert rows(locate(odd, make_queries(spark, patterns), method="native")) == truth(patterns)
    with pytest.raises(ValueError):
        make_queries(spark, [""])
    with pytest.raises(ValueError):
        locate(odd, spark.createDataFrame([("1", None, "", None)], "query_id string, stream_id string, pattern string, at_seq bigint"))


def test_empty_input(spark, odd):
    none = odd.where("false")
    for method in ("index", "catalyst", "auto"):
        assert locate(none, make_queries(spark, ["a"]), method=method).count() == 0
        assert locate(odd, make_queries(spark, []), method=method).count() == 0
    assert tail_table(none).count() == 0


def test_locate_array_and_sampled_queries(spark, odd):
    q = sample_queries(spark.createDataFrame([("d", "ab" * 40)], "stream_id string, text string"), [2, 5], 3)
    found = locate(odd, q, method="index").groupBy("query_id").count().collect()
    assert len(found) == 6 and locate_array(odd, make_queries(spark, ["x"])).first()["offs"] == [0]


def test_relational_tail_is_the_kernels(spark, sf_dir):
    for name, capacity in (("ev_user", 64), ("conv", 256), ("li_part", 32)):
        texts_ = family(spark, sf_dir, name)
        a = tail_table(window_at(texts_, capacity)).select("stream_id", "n_seen", "tail_start", "tail_len", "kind", "twin", "period")
        last = replay_tails(texts_, capacity)
        b = last.join(texts_.select("stream_id", F.length("text").cast("long").alias("n_seen")), ["stream_id", "n_seen"])
        assert rows(a.na.fill(-1)) == rows(b.select(a.columns).na.fill(-1))


def test_adapters_round_trip(spark, sf_dir):
    y = symbols(load(spark, sf_dir, "events"), "user_id", ["ts", "event_id"], "left(event_type, 1)")
    assert rows(assemble(y)) == rows(family(spark, sf_dir, "ev_user").select("stream_id", "text"))
    coded, codes = encode_symbols(y.where("sym <> 'p'"))
    assert coded.count() == y.where("sym <> 'p'").count() and codes.count() == 4
    # A symbol that arrives gets a new code; those known keep theirs.
    coded, more = encode_symbols(y, codes)
    old = {r.sym: r.code for r in codes.collect()}
    new = {r.sym: r.code for r in more.collect()}
    assert coded.count() == y.count() and sorted(old.values()) == [0, 1, 2, 3] and new == old | {"p": 4}
    t = family(spark, sf_dir, "conv")
    assert rows(assemble(chunks(t, 100).select("stream_id", F.col("chunk_no").alias("seq"), F.col("text").alias("sym")))) == rows(t)


@pytest.mark.parametrize("hot", [False, True])
def test_segments_and_seams(spark, hot):
    text = "abcabcabxabcabcab" * 9 + "abcab"
    t = spark.createDataFrame([("s", text)], "stream_id string, text string")
    patterns = ["ab", "xabcabc", "bxabcabcababcabcabx", "zz", text[5:90]]
    for capacity in (None, 40):
        found = locate_segmented(seal_segments(chunks(t, 7), 5, hot), make_queries(spark, patterns), 5, capacity)
        want = sorted((p, i) for p in patterns for i in range(len(text) - len(p) + 1) if text[i : i + len(p)] == p and (capacity is None or i >= len(text) - capacity))
        assert sorted((r.query_id, r.off) for r in found.collect()) == want


def test_planner():
    assert planner.choose_method(1, 4096) == "native" and planner.choose_method(10_000, 4096) == "suffix_array"
    assert planner.may_contain(planner.gram_signature("abcdef"), planner.gram_signature("cde"))
    assert not planner.may_contain(planner.gram_signature("abcdef"), planner.gram_signature("xyz"))


def test_signature_and_measures(spark, sf_dir):
    w = window_at(family(spark, sf_dir, "ev_user"), 64)
    assert signature(family(spark, sf_dir, "ev_user")).count() == w.count()
    work = measures.query_work(w, ["e", "ev"])
    assert work.where("steps > 6 * (m + occ + 1)").count() == 0
    text = spark.createDataFrame([("abcde" * 900,)], "win_text string")
    # The index's steps follow the answer, a scan's the window: of a rare pattern the ratio grows with it.
    text = text.unionByName(spark.createDataFrame([("ab" * 2000 + "c" + "ab" * 20,)], "win_text string"))
    kmp = {r.w: r.ratio for r in measures.work_vs_baseline(text, ["bca"], [64, 512, 4000]).where("method = 'kmp'").collect()}
    assert 2 * kmp[64] < kmp[512] and 4 * kmp[512] < kmp[4000]
    label, median, least, n = measures.timing("x", lambda: 3, 2)
    assert (label, n) == ("x", 3) and least <= median


def test_sources_and_sinks(spark, tmp_path):
    register_source(spark)
    made = spark.read.format("symbols").option("text", "abc").option("n", "7").load()
    assert [r.sym for r in made.orderBy("seq").collect()] == list("abcabca")
    save_parquet(made, f"{tmp_path}/out", ["sym"])
    assert spark.read.parquet(f"{tmp_path}/out").count() == 7
    (tmp_path / "t.csv").write_text("k,v\na,1\n")
    assert load_text(spark, f"{tmp_path}/t.csv", "csv", "k string, v int").first()["v"] == 1
    (tmp_path / "t.txt").write_text("one\ntwo")
    assert load_text(spark, f"{tmp_path}/t.txt", whole=True).count() == 1


def test_live_window_over_batches(spark, tmp_path):
    """The same answers however the input is cut into micro-batches, for every state layout."""
    text, ask = "abcabcabxab" * 3, {5, 12, 30}
    events = [("s", 2 * i, "sym", c) for i, c in enumerate(text)] + [("s", 2 * i + 1, "query", "ab") for i in ask]
    schema = "stream_id string, seq bigint, kind string, payload string"
    want = sorted((i + 1, j) for i in ask for j in range(max(0, i + 1 - 8), i) if text[j : j + 2] == "ab" and j + 2 <= i + 1)
    for layout in ("text", "text+lazy", "tree"):
        for cut in (1, 3):
            src = tmp_path / f"{layout}{cut}"
            events.sort(key=lambda e: e[1])
            step = -(-len(events) // cut)
            for k in range(cut):
                spark.createDataFrame(events[k * step : (k + 1) * step], schema).coalesce(1).write.mode("append").parquet(str(src))
            stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(str(src))
            with state_store(spark):
                q = to_memory(live_locate(stream, 8, layout), f"live{layout[:5].replace('+', '_')}{cut}", str(tmp_path / f"c{layout}{cut}"))
                q.awaitTermination()
            assert sorted((r.n_seen, r.off) for r in spark.table(f"live{layout[:5].replace('+', '_')}{cut}").collect()) == want


def test_event_time_streams(spark, sf_dir, tmp_path):
    from winsub.sources.readers import stream_table

    events = stream_table(spark, sf_dir, "events")
    q = upsert_batches(once(events, ["event_id"], "ts", "1 hour"), f"{tmp_path}/o", f"{tmp_path}/c1")
    q.awaitTermination()
    assert spark.read.parquet(f"{tmp_path}/o").count() == load(spark, sf_dir, "events").count()
    for k, options in enumerate(({"size": "1 hour"}, {"size": "1 hour", "slide": "15 minutes"}, {"size": "30 minutes", "session": True, "key": "user_id"})):
        q = to_memory(counts(events, "ts", "1 hour", **options), f"counts{k}", f"{tmp_path}/w{k}")
        q.awaitTermination()
        assert spark.table(f"counts{k}").count() > 0


def test_reordered_symbols_and_late_ones(spark, tmp_path):
    schema = "stream_id string, ts timestamp, seq bigint, payload string"
    at = lambda s: f"2024-01-01 00:{s // 60:02d}:{s % 60:02d}"
    for k, batch in enumerate([[(5, "b"), (1, "a"), (9, "d")], [(7, "c"), (60, "e")], [(2, "late"), (200, "f")], [(400, "g")]]):
        rows = spark.createDataFrame([("s", at(s), s, p) for s, p in batch], "stream_id string, ts string, seq bigint, payload string").withColumn("ts", F.col("ts").cast("timestamp"))
        rows.coalesce(1).write.mode("append").parquet(f"{tmp_path}/{k}")
    stream = spark.readStream.schema(schema).option("maxFilesPerTrigger", 1).parquet(f"{tmp_path}/[0-9]")
    with state_store(spark):
        to_memory(reordered(stream, "10 seconds"), "ordered", f"{tmp_path}/c").awaitTermination()
    got = spark.table("ordered").collect()
    assert [r.payload for r in got if not r.late][:5] == list("abcde") and [r.payload for r in got if r.late] == ["late"]


def test_stream_stream_join(spark, sf_dir, tmp_path):
    from winsub.sources.readers import stream_table

    events = stream_table(spark, sf_dir, "events").select("user_id", "ts", "event_type", "event_id")
    a, b = events.where("event_type = 'purchase'"), events.where("event_type = 'error'")
    joined = near_events(a, b, "user_id", "10 minutes").select(F.col("a.event_id").alias("x"), F.col("b.event_id").alias("y"))
    to_memory(joined, "met", f"{tmp_path}/j").awaitTermination()
    e = load(spark, sf_dir, "events")
    want = e.where("event_type = 'purchase'").alias("a").join(e.where("event_type = 'error'").alias("b"), F.expr("a.user_id = b.user_id and b.ts between a.ts - interval 10 minutes and a.ts + interval 10 minutes"))
    assert spark.table("met").count() == want.count()


def plan(df):
    return df._jdf.queryExecution().toString()


def test_filters_and_columns_reach_the_scan(spark, sf_dir):
    from winsub.relational_workloads import QUERIES as REL

    text = plan(REL["rel_prefix_filter"](spark, sf_dir))
    assert "StringStartsWith(text,The)" in text and "ReadSchema: struct<doc_id:bigint,text:string,lang:string>" in text
    text = plan(tail_table(window_at(family(spark, sf_dir, "doc"), 64)).select("stream_id", "tail_len"))
    assert "Exchange" not in text and "Python" not in text and "ReadSchema: struct<doc_id:bigint,text:string>" in text
    text = plan(locate(window_at(family(spark, sf_dir, "li_part"), 32), make_queries(spark, ["RN"]), method="index"))
    assert text.split("== Physical Plan ==")[1].count("Exchange hashpartitioning") == 1  # the assembly of streams


def test_windows_are_cut_before_they_are_gathered(spark, sf_dir):
    for name, capacity in (("ev_user", 16), ("ev_all", 300), ("ev_all", 1200), ("li_part", 32), ("ord_cust", 5), ("ord_prio", 3), ("conv", 64), ("doc", 40)):
        assert rows(family_window(spark, sf_dir, name, capacity)) == rows(window_at(family(spark, sf_dir, name), capacity))
    for name, capacity in (("ev_user", 16), ("li_part", 4096)):
        text = plan(family_window(spark, sf_dir, name, capacity)).split("== Physical Plan ==")[1]
        # Partial limits run before the exchange; only what they leave is collected.
        assert text.count("WindowGroupLimit") >= 2 and "Partial" in text and "collect_list" in text
    text = plan(family_window(spark, sf_dir, "ev_all", 300)).split("== Physical Plan ==")[1]
    assert "TakeOrderedAndProject(limit=300" in text or "WindowGroupLimit" in text


def test_places_of_a_stream_that_holds_most_rows(spark):
    data = [("hot", (i * 7919) % 5000, i) for i in range(5000)] + [(f"k{i % 50}", i, i) for i in range(200)] + [("hot", 3, -1)]
    df = spark.createDataFrame(data, "k string, at long, v long").repartition(5)
    got = numbered(df, ["k"], ["at", "v"]).collect()
    for key in ("hot", "k3"):
        own = sorted((r for r in got if r.k == key), key=lambda r: (r["at"], r.v))
        assert [r.seq for r in own] == list(range(len(own)))
    assert numbered(df.where("false"), ["k"], ["at"]).count() == 0


def test_segments_from_symbols(spark, sf_dir, tmp_path):
    made = symbol_chunks(family_symbols(spark, sf_dir, "ev_all"), 64)
    assert rows(made) == rows(chunks(family(spark, sf_dir, "ev_all"), 64))
    sealed = seal_segments(made, 5)
    text = plan(sealed).split("== Physical Plan ==")[1]
    assert "lead(" not in text and text.count("Window [") == 1  # that of the ranges' counts alone
    text = family(spark, sf_dir, "ev_all").first()["text"]
    assert all(r.text + r.overlap == text[r.base_off : r.base_off + len(r.text) + 4] for r in sealed.collect())
    live = expire_segments(made, 100)
    assert {r.chunk_no for r in live.collect()} == {k for k in range(-(-len(text) // 64)) if min(len(text), (k + 1) * 64) > len(text) - 100}
    users = seal_segments(symbol_chunks(family_symbols(spark, sf_dir, "ev_user"), 16), 4)
    write_index(users, f"{tmp_path}/index")
    assert rows(read_index(spark, f"{tmp_path}/index")) == rows(users)
    some = read_index(spark, f"{tmp_path}/index", ["3", "7", "none"])
    assert rows(some) == rows(users.where("stream_id in ('3', '7')")) and "PartitionFilters: [bucket" in plan(some)


def test_sets_too_large_to_send(spark, odd, monkeypatch):
    monkeypatch.setattr(planner, "SENT_QUERIES", 1)
    patterns = ["ab", "ba", "ababababab", "zz"]
    q = make_queries(spark, patterns)
    found = leaf_hits(tail_table(odd), q).unionByName(tail_hits(tail_table(odd), q))
    assert sorted((r.stream_id, r.query_id, r.n_seen, r.off) for r in found.collect()) == truth(patterns)
    assert "BroadcastNestedLoopJoin" not in plan(found).split("== Physical Plan ==")[1]
    with pytest.raises(ValueError):
        tail_case_split(odd, q)
    with pytest.raises(ValueError):
        count_matches(odd, q)
    assert {(r.stream_id, r.query_id): r.cnt for r in count_matches(odd, q, zeros=False).collect()}[("d", "ab")] == 30


def test_large_windows_are_refused(spark):
    w = window_at(spark.createDataFrame([("a", "ab" * 40)], "stream_id string, text string"), 80)
    with pytest.raises(Exception, match="at most 64"):
        tree_nodes(w, tail_table(w)).collect()


def test_staged_folders(spark):
    class Cluster:
        class conf:
            get = staticmethod(lambda *a: None)

        class sparkContext:
            master = "local-cluster[2,1,1024]"
            getCheckpointDir = staticmethod(lambda: None)

    with pytest.raises(ValueError):
        shared_folder(Cluster)
    path = staged(spark.range(3), "three").inputFiles()[0]
    import os

    folder = os.path.dirname(os.path.dirname(path.removeprefix("file://")))
    assert os.path.isdir(folder)
    drop_staged()
    assert not os.path.exists(folder)


def test_snapshots_are_compact():
    import random

    r = random.Random(1)
    text = "".join(r.choice("abcde") for _ in range(6000))
    for capacity in (64, 4096):
        x = WindowIndex(capacity).extend(text)
        assert len(x.snapshot()) < (40 if capacity > 64 else 60) * capacity
        y = WindowIndex.restore(x.snapshot())
        for z in "abcabcaaaab" * 40:
            x.push(z)
            y.push(z)
        assert all(x.locate(p) == y.locate(p) for p in ("a", "abc", "ba", "zz")) and {k: v for k, v in x.steps.items() if k != "order_moves"} == {k: v for k, v in y.steps.items() if k != "order_moves"}
        assert x.footprint()["tree_nodes"] == y.footprint()["tree_nodes"] <= 2 * capacity


def test_measures_by_definition(spark, sf_dir):
    """Alphabet, node counts and scan steps worked out apart from the operators."""
    w = window_at(family(spark, sf_dir, "part_name"), 1 << 30).limit(5)
    texts_ = {r.stream_id: r.win_text for r in w.collect()}
    for r in measures.alphabet_factor(w, ["a"]).collect():
        assert r.sigma == len(set(texts_[r.stream_id])) and r.compares >= 0
    for r in measures.footprint(w).collect():
        t = texts_[r.stream_id]
        tail = max(k for k in range(len(t)) if not k or t[-k:] in t[:-1])
        inner = {t[i : i + d] for i in range(len(t) - tail) for d in range(len(t) - i) if len({t[j + d] for j in range(len(t) - tail) if t.startswith(t[i : i + d], j) and j + d < len(t)}) > 1} | {""}
        assert (r.w, r.link_nodes, r.tree_nodes) == (len(t), len(inner), len(inner) + len(t) - tail)
    steps = dict(measures.steps_by_method("ab" * 300, "zz", 600))
    assert steps["kmp"] >= 600 and steps["boyer_moore"] >= 300 and steps["index"] <= 6 * 3


def test_rate_source_and_update_mode(spark, tmp_path):
    stream = symbol_rate(spark, 50, "abc")
    query = stream.writeStream.format("memory").queryName("rated").option("checkpointLocation", f"{tmp_path}/r").start()
    try:
        import time

        for _ in range(40):
            if query.lastProgress and query.lastProgress["batchId"] >= 1 and spark.table("rated").count():
                break
            time.sleep(0.5)
        got = spark.table("rated").collect()
    finally:
        query.stop()
    assert got and all(r.sym == "abc"[r.seq % 3] for r in got)
    source = f"{tmp_path}/in"
    spark.createDataFrame([("x",), ("y",), ("x",)], "k string").coalesce(1).write.parquet(source)
    spark.createDataFrame([("x",)], "k string").coalesce(1).write.mode("append").parquet(source)
    counted = spark.readStream.schema("k string").option("maxFilesPerTrigger", 1).parquet(source).groupBy("k").count()
    to_memory(counted, "updated", f"{tmp_path}/u", "update").awaitTermination()
    # Only changed rows come out of each batch.
    found = spark.table("updated").collect()
    assert max(r["count"] for r in found if r.k == "x") == 3 and [r["count"] for r in found if r.k == "y"] == [1]


def test_idle_windows_have_a_lifetime():
    """The lifetime reaches the state; a window whose state is gone starts afresh."""
    import pandas as pd

    class State:
        value = None

        def exists(self):
            return self.value is not None

        def get(self):
            return self.value

        def update(self, value):
            self.value = value

    class Handle:
        def getValueState(self, name, schema, ttl=None):
            self.ttl, self.state = ttl, State()
            return self.state

    rows = lambda *x: iter([pd.DataFrame(x, columns=["seq", "kind", "payload"])])
    for idle in (None, 1000):
        handle, live = Handle(), LiveWindow(8, "text", idle)
        live.init(handle)
        assert handle.ttl == idle
        list(live.handleInputRows(("s",), rows((0, "sym", "a"), (1, "sym", "b")), None))
        assert list(pd.concat(live.handleInputRows(("s",), rows((2, "query", "ab")), None)).off) == [0]
        handle.state.value = None  # expired
        assert pd.concat(live.handleInputRows(("s",), rows((3, "query", "ab")), None)).empty


def test_grams_are_counted_where_their_text_is(spark, monkeypatch):
    texts = ["abababab", "", "aé€😀\0\n" * 3, "abc", "".join(map(chr, range(300, 700)))]
    for together in (7, 1 << 17):
        monkeypatch.setattr(features, "TOGETHER", together)
        for q in (1, 4, 9):  # grams of nine letters out of 400 pass 63 bits
            found = [(i, g, n) for at, grams, counts in count_grams(texts, q) for i, g, n in zip(at.tolist(), grams.to_pylist(), counts.tolist(), strict=True)]
            want = [(i, t[k : k + q]) for i, t in enumerate(texts) for k in range(len(t) - q + 1)]
            assert len(found) == len(set(want)) and all(n == want.count((i, g)) for i, g, n in found)
    once = qgram_features(spark.createDataFrame([("a", "ababab"), ("b", "aba"), (None, "xyzxyz")], "stream_id string, text string"), 4)
    assert sorted(map(tuple, once.collect()), key=repr) == [("a", "abab", 2), ("a", "baba", 1), (None, "xyzx", 1), (None, "yzxy", 1), (None, "zxyz", 1)]
    assert "Exchange" not in plan(once).split("== Physical Plan ==")[1]
    several = qgram_features(spark.createDataFrame([("a", "ababab"), ("a", "babab"), ("b", "abcd"), (None, "xyzw"), (None, "xyzw")], "stream_id string, text string"), 4)
    assert sorted(map(tuple, several.collect()), key=repr) == [("a", "abab", 3), ("a", "baba", 2), ("b", "abcd", 1), (None, "xyzw", 2)]


def test_work_builds_each_window_once(monkeypatch):
    made = []

    class Counted(WindowIndex):
        def __init__(self, *a, **b):
            made.append(1)
            super().__init__(*a, **b)

    text = "abracadabra" * 20
    apart = [measures.steps_by_method(text, p, 100) for p in ("abra", "zz", "a")]
    monkeypatch.setattr(measures, "WindowIndex", Counted)
    assert measures.steps_by_pattern(text, ["abra", "zz", "a"], 100) == apart and len(made) == 1
