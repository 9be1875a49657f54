"""Trees, languages, lattice, alignment, mining, post-processing, relations, sources and streams."""

import random

import numpy as np
import pytest
from pyspark.sql import functions as F

from motifspark import queries as Q
from motifspark.functions.columns import contains_expr, shadow_expr
from motifspark.functions.register import register
from motifspark.operators import baseline, kernel, log as L, mine, post, relations as R
from motifspark.operators.search import align_search, align_trace
from motifspark.plans.language import is_leftmost, is_subsequence, same_language, shadow_of_word, tail, words
from motifspark.plans.lattice import Candidate, all_trees, atomic_patterns, combinable, combine, construction_tree, next_level, regular_seeds
from motifspark.plans.seeds import is_loop_seed, is_seed, loop_seeds, seed_closure, seed_kinds
from motifspark.plans.tree import alt, canonical_word, leaf, loop, loop_block, nest, node, par, parse_tree, same_syntax, seq
from motifspark.sources import files, views as V
from motifspark.streaming import stream as S

SF = "/root/testdata/sf0.01"


def test_trees():
    t = parse_tree("seq(a,and(c,b))")
    assert t == seq("a", par("c", "b")) and t.depth == 2 and t.alphabet == {"a", "b", "c"} and str(parse_tree(str(t))) == str(t)
    assert same_syntax(t, parse_tree("seq(a,and(b,c))")) and canonical_word(t) == "seq(a,and(b,c))"
    assert nest("seq", ["a", "b", "c"]) == parse_tree("seq(a,b,c)") == seq("a", seq("b", "c"))
    deep = parse_tree("loop(loop(loop(seq(a,b),c),d),e)")
    assert loop_block(deep, (0, 0, 0, 0)) == () and loop_block(t, (1,)) == (1,)
    for bad in ("seq(a)", "foo(a,b)", "seq(a,b", "tau", "seq(a,b)c"):
        with pytest.raises(ValueError):
            parse_tree(bad)


def test_languages_and_words():
    assert words(parse_tree("seq(BT,and(CO,RB))")) == {("BT", "CO", "RB"), ("BT", "RB", "CO")}
    assert words(loop("a", "b")) == {("a", "b", "a")} and words(loop("a", "b"), compact=False) == {("a",), ("a", "b", "a")}
    assert shadow_of_word(("a", "c", "b"), list("abcbb")) == [1, 3, 4] and is_leftmost(("a", "c", "b"), [1, 3, 4], list("abcbb"))
    assert not is_leftmost(("a", "c", "b"), [1, 3, 5], list("abcbb")) and tail(["a", "b"], 2) == []
    assert same_language(parse_tree("seq(a,seq(b,c))"), parse_tree("seq(seq(a,b),c)"))


def test_lattice_is_complete_and_seeds_are_unique():
    for n, d in ((3, 2), (4, 2), (4, 3)):
        level, seen = atomic_patterns("abcd"[:n]), set()
        while level:
            seen |= {canonical_word(t) for t in level}
            level = [c.tree for c in next_level(level, {}, d, 0).values()]
        assert seen == all_trees(list("abcd"[:n]), d)
    for w in sorted(all_trees(list("abcd"), 3))[::17]:
        t = parse_tree(w)
        s1, s2, a, b = regular_seeds(t)
        if t.n_leaves > 2:
            assert combinable(s1, s2) and w in {c.pid for op in ("seq", "and", "loop") for c in combine(s1, s2, op)}
    assert construction_tree(parse_tree("seq(a,and(b,c))")) == {"seq(a,b)", "seq(a,c)", "a", "b", "c"}


def test_seeds():
    assert len(seed_closure(parse_tree("seq(seq(a,b),seq(c,d))"))) == 15
    kinds = seed_kinds(parse_tree("seq(seq(a,b),seq(c,d))"))
    assert len(kinds) == 14 and {w for w, k in kinds.items() if k == "regular"} == {"seq(seq(a,b),c)", "seq(seq(a,b),d)"}
    for w in sorted(all_trees(list("abcd"), 2, ("seq", "and", "loop", "xor")))[::23]:
        t = parse_tree(w)
        for u in seed_closure(t):
            assert str(u) == w or is_seed(u, t)
    assert loop_seeds(loop("a", "b")) == {"seq(a,b)"} and is_loop_seed(seq("a", "b"), loop("a", "b"))


def random_tree(rng, acts, ops):
    if len(acts) == 1:
        return leaf(acts[0])
    k = rng.randrange(1, len(acts))
    return node(rng.choice(ops), random_tree(rng, acts[:k], ops), random_tree(rng, acts[k:], ops))


def coded(traces):
    codes = {a: i for i, a in enumerate("abcdefg")}
    flat = np.array([codes[x] for t in traces for x in t], np.int32)
    return kernel.Traces(kernel.pad(flat, np.concatenate(([0], np.cumsum([len(t) for t in traces])))), codes)


def test_scan_search_and_words_agree():
    rng = random.Random(5)
    traces = [[rng.choice("abcdef") for _ in range(rng.randrange(0, 16))] for _ in range(150)]
    for _ in range(60):
        t = random_tree(rng, rng.sample("abcdef", rng.randrange(2, 6)), ("seq", "and", "loop", "xor"))
        tr = coded(traces)
        m = kernel.scan(tr, t, np.arange(tr.rows), np.zeros(tr.rows, np.int32))
        own = words(t)
        for i, x in enumerate(traces):
            hit = bool(m.end[i] < tr.far)
            found = align_trace(t, x)
            assert hit == found.hit == any(is_subsequence(w, x) for w in own)
            if hit:
                assert found.places[-1] == m.end[i]


def test_growth_equals_scan():
    rng = random.Random(7)
    traces = [[rng.choice("abcdef") for _ in range(rng.randrange(0, 22))] for _ in range(300)]
    tried = 0
    for _ in range(400):
        t = random_tree(rng, rng.sample("abcdef", rng.randrange(2, 7)), ("seq", "and", "loop"))
        s1, s2, _, _ = regular_seeds(t)
        path = max(p for p, x in t.leaves() if len(p) == t.depth)[:-1]
        tr = coded(traces)
        rows, zero = np.arange(tr.rows), np.zeros(tr.rows, np.int32)
        one, two, full = (kernel.scan(tr, x, rows, zero, shared=False) for x in (s1, s2, t))
        hit = full.end < tr.far
        for loops in ("grown", "realigned"):
            got = kernel.grow(tr, t, path, one.at, two.at, (one.end < tr.far) & (two.end < tr.far), loops=loops)
            assert ((got.end < tr.far) == hit).all()
            for s, p in full.at.items():
                assert (got.at[s][hit] == p[hit]).all(), (str(t), s)
        tried += int(hit.sum())
    assert tried > 1000


def test_worked_examples():
    for trace, tree, places in (
        ("acabcbde", "seq(loop(a,c),and(d,e))", (1, 2, 3, 7, 8)), ("acabcbde", "seq(loop(b,c),and(d,e))", (4, 5, 6, 7, 8)), ("acabcbde", "seq(loop(seq(b,a),c),and(d,e))", None),
        ("cbad", "seq(xor(a,b),d)", (2, 4)), ("cbad", "seq(xor(a,c),d)", (1, 4)), ("cbad", "seq(xor(a,seq(b,c)),d)", (3, 4)), ("abcbb", "seq(a,and(b,c))", (1, 2, 3)), ("", "seq(a,b)", None),
    ):
        found = align_trace(parse_tree(tree), list(trace))
        assert (found.places if found.hit else None) == places
    t = parse_tree(Q.GROWTH_TREE)
    tr = coded([Q.GROWTH_TRACE.split()])
    row, zero, valid = np.array([0]), np.zeros(1, np.int32), np.array([True])
    s1, s2, _, _ = regular_seeds(t)
    work = kernel.Work()
    m = kernel.grow(tr, t, (0, 0, 0), kernel.scan(tr, s1, row, zero).at, kernel.scan(tr, s2, row, zero).at, valid, work)
    assert {s[0]: int(p[0]) for s, p in m.at.items()} == {"b": 5, "a": 7, "c": 9, "d": 10, "f": 11, "e": 12}
    assert (work.realigned, work.reused) == (2, 4)


def test_columns_agree_with_kernel(spark):
    rng = random.Random(11)
    log = Q.literal_log(spark, {str(i): " ".join(rng.choice("abcde") for _ in range(rng.randrange(0, 14))) for i in range(120)}).withColumn("case_id", F.col("case_id"))
    rows = {r["case_id"]: r["acts"] for r in log.collect()}
    for text in ("seq(a,and(b,c))", "loop(a,xor(b,c))", "and(seq(a,b),loop(c,d))", "seq(xor(a,b),seq(c,d))"):
        t = parse_tree(text)
        got = {r["case_id"]: (r["hit"], r["s"]) for r in log.select("case_id", contains_expr(t).alias("hit"), shadow_expr(t).alias("s")).collect()}
        for k, acts in rows.items():
            found = align_trace(t, acts)
            assert got[k][0] == found.hit and (not found.hit or max(got[k][1]) == found.places[-1])
    register(spark)
    log.createOrReplaceTempView("small_log")
    n = spark.sql("SELECT count(*) AS n FROM small_log WHERE tree_contains(acts, 'seq(a,and(b,c))')").first()["n"]
    assert n == log.where(contains_expr("seq(a,and(b,c))")).count()
    assert align_search(log, parse_tree("seq(a,b)")).where("lo is not null").count() == log.where(contains_expr("seq(a,b)")).count()


def test_golden_mining_and_post(spark):
    log = V.log_cust_status(spark, SF)
    got = mine.mine_patterns(log, 0.7)
    assert len(got.frequent) == 30 and got.patterns.count() == 21 and post.postprocess(got.patterns).count() == 19
    assert got.frequent["seq(P,and(F,O))"] == 1140 and got.frequent["and(F,and(O,P))"] == 1332 and got.frequent["loop(xor(F,O),P)"] == 1300
    paper = mine.mine_patterns(log, 0.7, choice_rule="paper", mode="scan")
    assert paper.frequent["loop(xor(F,O),P)"] == 1260
    assert mine.mine_patterns(log, 0.7, compress=False, mode="scan").frequent == got.frequent
    assert mine.mine_patterns(log, 0.7, and_order="match").patterns.count() == 21
    assert mine.mine_patterns(L.empty_log(spark), 0.7).patterns.count() == 0
    with pytest.raises(mine.TooManyCandidates):
        mine.mine_patterns(log, 0.1, max_candidates=3)
    conv = mine.mine_patterns(V.log_conv(spark, SF), 0.7)
    assert len(conv.frequent) == 5 and post.postprocess(conv.patterns).count() == 3
    nodes, edges = R.build_graph(conv, post.postprocess(conv.patterns))
    assert "pid" in R.graph_json(nodes, edges).first()["json"] and R.to_dot(nodes, edges).startswith("digraph")
    again = post.postprocess(post.postprocess(got.patterns))
    assert {r["pid"] for r in again.collect()} == {r["pid"] for r in post.postprocess(got.patterns).collect()}


def test_transitive_reduction():
    assert R.transitive_reduction({("a", "b"), ("b", "c"), ("a", "c"), ("c", "d"), ("a", "d")}) == {("a", "b"), ("b", "c"), ("c", "d")}
    assert R.transitive_reduction({("a", "b"), ("b", "a"), ("b", "c"), ("a", "c")}) >= {("a", "b"), ("b", "a")}


def test_file_sources(spark, tmp_path):
    (tmp_path / "log.csv").write_text("case,at,act\n1,2024-01-02,b\n1,2024-01-01,a\n2,2024-01-01,\n2,2024-01-03,c\n")
    got = {r["case_id"]: r["acts"] for r in files.read_log_csv(spark, str(tmp_path / "log.csv"), "case", "at", "act").collect()}
    assert got == {"1": ["a", "b"], "2": ["c"]}
    (tmp_path / "log.json").write_text('{"case":"1","at":"2024-01-01","act":"a"}\n{"case":"1","at":"2024-01-02","act":"b"}\n')
    assert files.read_log_json(spark, str(tmp_path / "log.json"), "case", "at", "act").first()["acts"] == ["a", "b"]
    event = lambda a: f'<event><string key="concept:name" value="{a}"/><date key="time:timestamp" value="2024-01-01T00:00:00"/></event>'
    (tmp_path / "log.xes").write_text(f'<log><trace><string key="concept:name" value="t1"/>{event("a")}{event("b")}</trace></log>')
    assert [tuple(r) for r in files.read_log_xes(spark, str(tmp_path / "log.xes")).select("case_id", "acts").collect()] == [("t1", ["a", "b"])]


def test_stream_state_equals_batch(spark, tmp_path):
    rng = random.Random(2)
    machine = S.Progress(parse_tree("seq(a,and(b,loop(c,d)))"))
    for _ in range(200):
        trace = [rng.choice("abcd") for _ in range(12)]
        ends, done = [0] * len(machine.program), None
        for i, a in enumerate(trace, 1):
            machine.advance(ends, a, i)
            done = done or (i if ends[-1] else None)
        found = align_trace(parse_tree("seq(a,and(b,loop(c,d)))"), trace)
        assert (done is not None) == found.hit and (not found.hit or done == found.places[-1])
    rows = [(i, i % 3, rng.choice(["click", "error", "view"])) for i in range(60)]
    spark.createDataFrame(rows, "event_id long, user_id long, event_type string").coalesce(1).write.parquet(str(tmp_path / "in"))
    source = spark.readStream.schema("event_id long, user_id long, event_type string").parquet(str(tmp_path / "in"))
    out = S.open_cases(source, "user_id", "event_type", ["event_id"], ["seq(click,error)"])
    run = out.writeStream.format("memory").queryName("done_cases").option("checkpointLocation", str(tmp_path / "ck")).trigger(availableNow=True).start()
    run.awaitTermination()
    got = {(r["key"], r["pos"]) for r in spark.table("done_cases").collect()}
    want = set()
    for u in range(3):
        f = align_trace(seq("click", "error"), [a for _, k, a in rows if k == u])
        if f.hit:
            want.add((str(u), f.places[-1]))
    assert got == want


def test_queries_match_sql_on_a_sample(spark):
    duckdb = pytest.importorskip("duckdb")
    con = duckdb.connect()
    for t in "region nation customer orders lineitem part events conversations".split():
        con.sql(f"create view {t} as select * from '{SF}/{t}.parquet'")
    for name in ("log_conv", "pair_stats_conv", "mine_cust_status_d2_regular", "rel_spans_cust", "growth_reuse_counts", "boundary_cust", "stream_support_events"):
        df, want = Q.QUERIES[name](spark, SF), con.sql(Q.SQL[name])
        cols = sorted(df.columns)
        at = [want.columns.index(c) for c in cols]
        assert sorted((tuple(r[c] for c in cols) for r in df.collect()), key=str) == sorted((tuple(r[i] for i in at) for r in want.fetchall()), key=str), name


def test_imports_stay_apart():
    from pathlib import Path

    root = Path(__file__).resolve().parent.parent / "motifspark"
    for f in root.rglob("*.py"):
        if "llm" not in f.relative_to(root).parts:
            assert "motifspark.llm" not in f.read_text() and "corpus_pipeline" not in f.read_text(), f


def test_alt_is_a_choice():
    assert str(alt("a", "b")) == "xor(a,b)"


def test_regrown_and_stored_places_agree(spark, monkeypatch):
    rng = random.Random(3)
    log = Q.literal_log(spark, {str(i): " ".join(rng.choice("abcd") for _ in range(rng.randrange(0, 16))) for i in range(80)})
    kinds = {p: mine.mine_patterns(log, 0.4, max_depth=3, choices=False, places=p) for p in ("regrown", "stored")}
    scan = mine.mine_patterns(log, 0.4, max_depth=3, choices=False, mode="scan")
    assert kinds["regrown"].frequent == kinds["stored"].frequent == scan.frequent and len(scan.frequent) > 50
    work = [[(c["reused"], c["realigned"]) for c in k.counters] for k in kinds.values()]
    assert work[0] == work[1]


def test_places_beyond_their_room_are_grown_again():
    rng = random.Random(5)
    codes = {a: i for i, a in enumerate("abc")}
    tr = coded([[rng.choice("abc") for _ in range(10)] for _ in range(50)])
    known = {}
    for c in (Candidate(t, (), t.left.label, t.right.label) for t in atomic_patterns(codes)):
        known[c.pid] = c
    wide, narrow = mine.Places(tr, known), mine.Places(tr, known, room=0)
    for pid in [*known, *reversed(list(known))]:
        own = wide[pid]
        assert (narrow[pid].hit == own.hit).all()
        for s, p in own.at.items():
            assert (narrow[pid].at[s][own.hit] == p[own.hit]).all()
    assert len(narrow._held) == 2 < len(wide._held)


def test_measures_of_reported_patterns(spark):
    log = V.log_cust_status(spark, SF)
    plain, none = mine.mine_patterns(log, 0.7), mine.mine_patterns(log, 0.7, maximality="none", measure_precision=True)
    assert {r["precision"] for r in plain.patterns.collect()} == {None} and {r["maximal"] for r in plain.patterns.collect()} == {True}
    rows = none.patterns.collect()
    assert all(0 < r["precision"] <= 1 for r in rows) and {r["pid"] for r in rows if r["maximal"]} == {r["pid"] for r in plain.patterns.collect()}
    general = {r["pid"] for r in mine.mine_patterns(log, 0.7, maximality="generalized").patterns.collect()}
    assert general == {r["pid"] for r in plain.patterns.collect()} - {w for t in none.trees for w in seed_kinds(t)}
    for wrong in ({"mode": "grow"}, {"maximality": "all"}, {"choice_rule": "x"}, {"and_order": "x"}, {"places": "x"}, {"loops": "x"}, {"max_depth": 0}):
        with pytest.raises(ValueError):
            mine.mine_patterns(log, **wrong)
    assert mine.mine_patterns(log, 0.7, loops="realigned").frequent == plain.frequent


def test_blocks_stay_within_their_bound(monkeypatch):
    import pyarrow as pa

    monkeypatch.setattr(mine, "CELLS", 1000)
    lengths = [1] * 900 + [400] * 5 + [5000]
    batch = pa.RecordBatch.from_arrays([pa.array([[0] * n for n in lengths], pa.list_(pa.int32())), pa.array([1] * len(lengths))], ["acts", "weight"])
    got = [acts.shape for acts, _ in mine.blocks(batch, ["weight"])]
    assert sum(r for r, _ in got) == len(lengths) and all(r * w <= 1000 or r == 1 for r, w in got)
    assert sum(b.num_rows for b in mine.gathered(iter([batch] * 3))) == 3 * len(lengths)
    tr = coded([list("abcdefg")] * 100)
    small = kernel.Traces(tr.acts, tr.codes, room=0)
    for a in "abcabc":
        assert (small.table(a) == tr.table(a)).all() and len(small._next) == 1


def test_depth_three_against_all_trees(spark):
    rng = random.Random(13)
    log = Q.literal_log(spark, {str(i): " ".join(rng.choice("abcd") for _ in range(rng.randrange(4, 18))) for i in range(60)})
    rows = [r["acts"] for r in log.collect()]
    got = mine.mine_patterns(log, 0.5, max_depth=3, choices=False).frequent
    want = {}
    for w in all_trees(list("abcd"), 3):
        own = words(parse_tree(w))
        if (n := sum(any(is_subsequence(x, acts) for x in own) for acts in rows)) >= 30:
            want[w] = n
    assert got == want and max(parse_tree(w).depth for w in want) == 3


def test_reduction_by_joins_and_pair_counts_in_chunks(spark):
    edges = [("a", "b"), ("b", "c"), ("a", "c"), ("c", "d"), ("a", "d"), ("x", "d")]
    table = spark.createDataFrame([(a, b, "spans", 1, 1, 1.0) for a, b in edges], R.EDGES)
    assert {tuple(r) for r in R.reduce_edges_joined(table, "spans").collect()} == R.transitive_reduction(set(edges))
    with pytest.raises(ValueError):
        R.reduce_edges_joined(table.union(spark.createDataFrame([("d", "a", "spans", 1, 1, 1.0)], R.EDGES)), "spans")
    coded_log, codes = mine.encode(V.log_conv(spark, SF))
    trees = [parse_tree(t) for t in Q.REL_CONV]
    assert {tuple(r) for r in R.pair_counts(coded_log, trees, codes, chunk=2).collect()} == {tuple(r) for r in R.pair_counts(coded_log, trees, codes).collect()}


def test_fragments_do_not_overlap(spark):
    log = Q.literal_log(spark, {"1": "a b a b b a", "2": "b a", "3": "a c b c a b"})
    coded_log, codes = mine.encode(log, compress=False)
    trees = [leaf("a"), seq("a", "b"), par("a", "b"), alt("b", "c")]
    want = [0] * 4
    for r in log.collect():
        for i, t in enumerate(trees):
            rest = r["acts"]
            while (f := align_trace(t, rest)).hit:
                want[i] += 1
                rest = rest[max(f.places) :]
    assert baseline.fragments(coded_log, trees, codes) == want
    assert baseline.determinism(seq("a", "b")) == 1 and baseline.determinism(alt("a", "b")) == 0.5


def test_removals_name_what_makes_them(spark):
    own = spark.createDataFrame([(t,) for t in ("seq(a,b)", "loop(a,b)", "seq(a,and(b,c))", "seq(a,c)")], "pid string")
    assert {tuple(r) for r in post.removals(own).collect()} >= {("seq(a,b)", "loop(a,b)", "loop"), ("seq(a,c)", "seq(a,and(b,c))", "regular")}


def _differences(spark, folder, name):
    """Rows of a query and of its SQL that the other one has not."""
    duckdb = pytest.importorskip("duckdb")
    from collections import Counter
    from pathlib import Path

    con = duckdb.connect()
    con.sql("set TimeZone = 'UTC'")
    for f in Path(folder).glob("*.parquet"):
        con.sql(f"create view {f.stem} as select * from read_parquet('{f}{'/*.parquet' if f.is_dir() else ''}')")
    df, want = Q.QUERIES[name](spark, str(folder)), con.sql(Q.SQL[name])
    at = [want.columns.index(c) for c in df.columns]
    own, other = Counter(map(tuple, df.collect())), Counter(tuple(r[i] for i in at) for r in want.fetchall())
    assert own
    return list((own - other).items()), list((other - own).items())


def _two_choices(spark, folder):
    """Conversations that show seq(xor(a,b),xor(c,d)), of which seq(a,xor(c,d)) is frequent at 0.3 and seq(b,xor(c,d)) is not."""
    rows = [(i, turn, role, "") for i, t in enumerate(["a c"] * 4 + ["b a c"] + ["a d"] * 4 + ["b a d"] + ["e"] * 10) for turn, role in enumerate(t.split())]
    spark.createDataFrame(rows, "conv_id long, turn long, role string, text string").write.parquet(f"{folder}/conversations.parquet")
    return "seq(xor(a-0,b-0),xor(c-0,d-0))"


def test_trees_of_two_choices_as_in_sql(spark, tmp_path):
    tree = _two_choices(spark, tmp_path)
    assert _differences(spark, tmp_path, "mine_conv_rich_d2") == ([], [])
    log = V.log_conv_rich(spark, str(tmp_path))
    made = {r["pid"]: r["compact"] for r in mine.mine_patterns(log, 0.3, choice_check="made").patterns.collect()}
    every = {r["pid"]: r["compact"] for r in mine.mine_patterns(log, 0.3).patterns.collect()}
    assert made[tree] is False and tree not in every and every == {t: c for t, c in made.items() if c}
    with pytest.raises(ValueError):
        mine.mine_patterns(log, choice_check="x")


def test_precise_trees_of_two_choices_as_in_sql(spark, tmp_path):
    tree = _two_choices(spark, tmp_path)
    assert _differences(spark, tmp_path, "mine_conv_rich_precise") == ([], [])
    assert tree in {r["tree"] for r in Q.QUERIES["mine_conv_rich_precise"](spark, str(tmp_path)).collect()}


def test_worked_examples_over_tables(spark):
    for name in ("equivalence_classes_fixture", "growth_example", "hole_keys_fixture", "is_seed_fixture", "loop_seeds_fixture", "running_example", "seed_closure_fixture", "words_and3", "words_loop2"):
        assert " events" in Q.SQL[name] or " orders" in Q.SQL[name], name
        assert _differences(spark, SF, name) == ([], []), name


def test_literal_classes(spark):
    own = spark.createDataFrame([(t,) for t in ("seq(a,seq(b,c))", "seq(seq(a,b),c)", "and(a,and(b,c))", "and(and(a,b),c)", "seq(a,and(b,c))")], "pid string")
    assert {r["representative"] for r in post.equivalence_classes(own).collect()} == {"seq(a,seq(b,c))", "and(a,and(b,c))", "seq(a,and(b,c))"}


def test_literal_growth(spark):
    log = Q.literal_log(spark, {"t": "a e f c b c a b c d f e"})
    got = Q.grown_places(log, "seq(and(seq(seq(b,a),c),d),and(e,f))", {a: a for a in "abcdef"}).collect()
    assert [r.asDict() for r in got] == [{"case_id": "t", "b": 5, "a": 7, "c": 9, "d": 10, "f": 11, "e": 12}]


def test_literal_running_example(spark):
    inside = ["BT CO RB", "BT RB CO", "XA BT CO RB", "BT XA RB CO", "CO BT CO RB", "BT BT RB CO", "BT CO XA RB", "RB BT CO RB", "BT RB XA CO"]
    log = Q.literal_log(spark, {str(i): t for i, t in enumerate([*inside, "CO RB BT", "BT CO", "RB XA"], 1)})
    assert {r["case_id"] for r in log.where(contains_expr("seq(BT,and(CO,RB))")).collect()} == {str(i) for i in range(1, 10)}
