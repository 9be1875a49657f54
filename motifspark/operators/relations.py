"""Order and containment relations between patterns, and the graph they make."""

from __future__ import annotations

import functools
import json
from collections.abc import Callable, Iterator

import numpy as np
import pyarrow as pa
from pyspark.sql import DataFrame
from pyspark.sql import functions as F
from pyspark.sql.window import Window

from motifspark.plans.tree import Tree, parse_tree

from . import kernel
from .log import store
from .mine import MiningResult, blocks, gathered

#: Boundaries (patterns times traces) that a task holds at a time.
PAIR_CELLS = 8 << 20
KINDS = ("follows", "spans", "inter_follows", "inter_spans")
EDGES = "src string, dst string, kind string, n_num bigint, n_den bigint, support double"


def pair_counts(coded: DataFrame, trees: list[Tree], codes: dict[str, int], chunk: int = 1024) -> DataFrame:
    """``src, dst, n_follows, n_spans, n_shared`` of ordered pairs that share a case.

    ``follows``: dst starts after src ends; ``spans``: src lies within dst. Pairs are compared inside each block
    of traces, and one row per pair and task is shuffled. Beyond ``chunk`` patterns each pass takes that many sources
    and targets, so that counters and boundaries of a task stay within a bound whatever the number of patterns.
    """
    parts = [trees[at : at + chunk] for at in range(0, len(trees), chunk)] or [[]]
    made = [coded.mapInArrow(_pair_kernel(src, dst, codes), PAIRS) for src in parts for dst in parts]
    return functools.reduce(DataFrame.union, made).groupBy("src", "dst").agg(*[F.sum(c).alias(c) for c in ("n_follows", "n_spans", "n_shared")])


PAIRS = "src string, dst string, n_follows bigint, n_spans bigint, n_shared bigint"


def _pair_kernel(sources: list[Tree], targets: list[Tree], codes: dict[str, int]) -> Callable:
    own = {str(t): t for t in [*sources, *targets]}
    at = {pid: i for i, pid in enumerate(own)}
    rows_of, cols_of = [at[str(t)] for t in sources], np.array([at[str(t)] for t in targets], np.int64)

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        total = np.zeros((3, len(sources), len(targets)), np.int64)
        for b in gathered(batches):
            for acts, (weight,) in blocks(b, ["weight"]):
                step = max(1, PAIR_CELLS // max(1, len(own)))
                for first in range(0, len(acts), step):
                    tr, w = kernel.Traces(acts[first : first + step], codes), weight.to_numpy()[first : first + step]
                    rows, zero = np.arange(tr.rows), np.zeros(tr.rows, np.int32)
                    lo, hi, hit = (np.zeros((len(own), tr.rows), t) for t in (np.int32, np.int32, bool))
                    for i, t in enumerate(own.values()):
                        m = kernel.scan(tr, t, rows, zero)
                        lo[i], hi[i] = kernel.boundaries(t, m.at)
                        hit[i] = m.end < tr.far
                    for k, i in enumerate(rows_of):
                        cases = np.nonzero(hit[i])[0]
                        both, wi = hit[cols_of][:, cases], w[cases]
                        x, y = lo[cols_of][:, cases], hi[cols_of][:, cases]
                        total[0, k] += (both & (hi[i, cases] < x)) @ wi
                        total[1, k] += (both & (x <= lo[i, cases]) & (hi[i, cases] <= y)) @ wi
                        total[2, k] += both @ wi
        src, dst = np.nonzero(total[2])
        pids = list(own)
        keep = np.array(rows_of, np.int64)[src] != cols_of[dst] if len(src) else np.zeros(0, bool)
        src, dst = src[keep], dst[keep]
        cols = [pa.array([pids[rows_of[i]] for i in src], pa.string()), pa.array([pids[cols_of[i]] for i in dst], pa.string())]
        yield pa.RecordBatch.from_arrays(cols + [pa.array(total[j, src, dst]) for j in range(3)], [x.split()[0] for x in PAIRS.split(", ")])

    return run


def relations(result: MiningResult, tau_follow: float = 0.7, tau_span: float = 0.7, trees: list[Tree] | None = None, inter_only_if_missing: bool = False) -> DataFrame:
    """Edges whose support is above (not equal to) its threshold; global kinds divide by all cases, inter kinds by the
    cases that show both patterns."""
    counts = pair_counts(result.log, trees if trees is not None else result.trees, result.codes)
    n = F.lit(result.n_cases).cast("long")
    kinds = [("follows", "n_follows", n, tau_follow), ("spans", "n_spans", n, tau_span), ("inter_follows", "n_follows", F.col("n_shared"), tau_follow), ("inter_spans", "n_spans", F.col("n_shared"), tau_span)]
    rows = F.array(*[F.struct(F.lit(k).alias("kind"), F.col(num).alias("n_num"), den.alias("n_den"), (F.col(num) / den > tau).alias("on")) for k, num, den, tau in kinds])
    edges = counts.select("src", "dst", F.inline(F.filter(rows, lambda r: r["on"])))
    edges = edges.select("src", "dst", "kind", "n_num", "n_den", F.round(F.col("n_num") / F.col("n_den"), 6).alias("support"))
    if inter_only_if_missing:
        own = edges.where(~F.col("kind").startswith("inter_")).select("src", "dst", F.concat(F.lit("inter_"), "kind").alias("kind"))
        edges = edges.join(own, ["src", "dst", "kind"], "left_anti")
    return edges


def condense(edges: list[tuple[str, str]]) -> dict[str, str]:
    """Least member of the strongly connected group of each node."""
    graph: dict[str, list[str]] = {}
    for a, b in edges:
        graph.setdefault(a, []).append(b)
        graph.setdefault(b, [])
    index: dict[str, int] = {}
    low: dict[str, int] = {}
    stack: list[str] = []
    on: set[str] = set()
    group: dict[str, str] = {}
    for root in sorted(graph):
        if root in index:
            continue
        todo = [(root, iter(graph[root]))]
        index[root] = low[root] = len(index)
        stack.append(root)
        on.add(root)
        while todo:
            v, it = todo[-1]
            w = next(it, None)
            if w is None:
                todo.pop()
                if todo:
                    low[todo[-1][0]] = min(low[todo[-1][0]], low[v])
                if low[v] == index[v]:
                    members = []
                    while True:
                        members.append(stack.pop())
                        on.discard(members[-1])
                        if members[-1] == v:
                            break
                    for m in members:
                        group[m] = min(members)
            elif w not in index:
                index[w] = low[w] = len(index)
                stack.append(w)
                on.add(w)
                todo.append((w, iter(graph[w])))
            elif w in on:
                low[v] = min(low[v], index[w])
    return group


def transitive_reduction(edges: set[tuple[str, str]]) -> set[tuple[str, str]]:
    """Edges without an alternative path. Members of a cycle keep a ring in the order of their names."""
    group = condense(sorted(edges))
    above: dict[str, set[str]] = {}
    inner: dict[str, set[str]] = {}
    for a, b in edges:
        if group[a] != group[b]:
            above.setdefault(group[a], set()).add(group[b])
    for x, g in group.items():
        inner.setdefault(g, set()).add(x)
    reach: dict[str, set[str]] = {}

    def reached(g: str) -> set[str]:
        todo = [(g, False)]
        while todo:
            x, ready = todo.pop()
            if x in reach:
                continue
            nxt = above.get(x, set())
            if ready:
                reach[x] = set(nxt).union(*[reach[y] for y in nxt]) if nxt else set()
            else:
                todo.append((x, True))
                todo += [(y, False) for y in nxt if y not in reach]
        return reach[g]

    direct = {(g, h) for g, hs in above.items() for h in hs if not any(h in reached(x) for x in hs if x != h)}
    kept = set()
    for g, h in direct:
        kept.add(min((a, b) for a, b in edges if group[a] == g and group[b] == h))
    for members in inner.values():
        ring = sorted(members)
        if len(ring) > 1:
            kept |= {(a, b) for a, b in zip(ring, ring[1:] + ring[:1], strict=True)}
    return kept


def reduce_edges(edges: DataFrame, kinds: tuple[str, ...] = ("follows", "spans"), max_edges: int = 1_000_000) -> DataFrame:
    """Transitive reduction of the named kinds on the driver (bounded: an error beyond); other kinds stay as they are."""
    rows = edges.where(F.col("kind").isin(*kinds)).select("src", "dst", "kind").limit(max_edges + 1).collect()
    if len(rows) > max_edges:
        raise ValueError(f"more than {max_edges} edges")
    kept = [(a, b, k) for k in kinds for a, b in transitive_reduction({(r["src"], r["dst"]) for r in rows if r["kind"] == k})]
    own = edges.sparkSession.createDataFrame(kept, "src string, dst string, kind string")
    return edges.where(~F.col("kind").isin(*kinds)).unionByName(edges.join(own, ["src", "dst", "kind"], "left_semi"))


def reduce_edges_joined(edges: DataFrame, kind: str, max_rounds: int = 40) -> DataFrame:
    """The same for one acyclic kind by joins alone: an edge goes if a path of two reachability steps replaces it.

    Reachability doubles its paths in each round; every round is written in the shared folder and read back. A cycle
    raises, as does a graph whose paths are not closed after ``max_rounds``.
    """
    own = store(edges.where(F.col("kind") == kind).select("src", "dst").distinct())
    reach, n = own, own.count()
    for _ in range(max_rounds):
        step = reach.alias("a").join(reach.alias("b"), F.col("a.dst") == F.col("b.src")).select("a.src", "b.dst")
        reach = store(reach.union(step).distinct())
        if (more := reach.count()) == n:
            break
        n = more
    else:
        raise RuntimeError(f"paths are not closed after {max_rounds} rounds")
    if not reach.where("src = dst").isEmpty():
        raise ValueError(f"{kind} has a cycle; use reduce_edges")
    long = own.alias("a").join(reach.alias("b"), F.col("a.dst") == F.col("b.src")).select("a.src", "b.dst").distinct()
    return own.join(long, ["src", "dst"], "left_anti")


def node_table(patterns: DataFrame, post: DataFrame | None = None) -> DataFrame:
    """``pid, tree, numbered_tree, support, size``: nodes grow with support; labels may be replaced by numbers."""
    own = patterns.join(post.select("pid"), "pid", "left_semi") if post is not None else patterns
    size = F.round(10 + 30 * F.col("support"), 3)
    rows = own.select("pid", "tree", "support", size.alias("size")).collect()
    labels = sorted(set().union(*[parse_tree(r["pid"]).alphabet for r in rows])) if rows else []
    number = {a: str(i) for i, a in enumerate(labels, 1)}

    def numbered(t: Tree) -> str:
        return number[t.label] if t.is_leaf else f"{t.op}({numbered(t.left)},{numbered(t.right)})"

    made = [(r["pid"], r["tree"], numbered(parse_tree(r["pid"])), r["support"], r["size"]) for r in rows]
    return patterns.sparkSession.createDataFrame(made, "pid string, tree string, numbered_tree string, support double, size double")


def legend(patterns: DataFrame) -> DataFrame:
    """``number, activity`` as used in numbered trees."""
    pids = [r["pid"] for r in patterns.select("pid").collect()]
    labels = sorted(set().union(*[parse_tree(p).alphabet for p in pids])) if pids else []
    return patterns.sparkSession.createDataFrame([(i, a) for i, a in enumerate(labels, 1)], "number int, activity string")


def build_graph(result: MiningResult, post: DataFrame, tau_follow: float = 0.7, tau_span: float = 0.7) -> tuple[DataFrame, DataFrame]:
    """Nodes and reduced edges of the patterns that post-processing leaves."""
    kept = {r["pid"] for r in post.select("pid").collect()}
    edges = relations(result, tau_follow, tau_span, [t for t in result.trees if str(t) in kept])
    return node_table(result.patterns, post), reduce_edges(edges)


def graph_json(nodes: DataFrame, edges: DataFrame) -> DataFrame:
    """One row with the graph as a JSON document."""
    n = nodes.agg(F.sort_array(F.collect_list(F.struct("pid", "tree", "numbered_tree", "support", "size"))).alias("nodes"))
    e = edges.agg(F.sort_array(F.collect_list(F.struct("src", "dst", "kind", "support"))).alias("edges"))
    return n.join(e).select(F.to_json(F.struct("nodes", "edges")).alias("json"))


def to_dot(nodes: DataFrame, edges: DataFrame) -> str:
    style = {"follows": "solid", "spans": "bold", "inter_follows": "dashed", "inter_spans": "dotted"}
    lines = [f"  {json.dumps(r['pid'])} [width={r['size'] / 20:.2f}];" for r in nodes.collect()]
    lines += [f"  {json.dumps(r['src'])} -> {json.dumps(r['dst'])} [style={style[r['kind']]}, label=\"{r['support']}\"];" for r in edges.collect()]
    return "digraph patterns {\n" + "\n".join(lines) + "\n}\n"


PAGE = """<!DOCTYPE html><html><head><meta charset="utf-8"><title>Patterns</title></head><body>
<svg id="g" width="1000" height="800" style="border:1px solid #ccc"></svg><pre id="s"></pre><script>
const G = %s, svg = document.getElementById("g"), ns = "http://www.w3.org/2000/svg", at = {};
let box = [0, 0, 1000, 800];
const show = () => svg.setAttribute("viewBox", box.join(" "));
const make = (kind, attrs, title) => { const x = document.createElementNS(ns, kind); for (const k in attrs) x.setAttribute(k, attrs[k]);
  if (title) { const t = document.createElementNS(ns, "title"); t.textContent = title; x.appendChild(t); x.onmouseover = () => document.getElementById("s").textContent = title; } svg.appendChild(x); return x; };
G.nodes.forEach((n, i) => { const a = 2 * Math.PI * i / G.nodes.length; at[n.pid] = [500 + 380 * Math.cos(a), 400 + 320 * Math.sin(a)]; });
const dash = { follows: "", spans: "", inter_follows: "6 4", inter_spans: "2 4" }, hue = { follows: "#36c", spans: "#c63", inter_follows: "#36c", inter_spans: "#c63" };
G.edges.forEach(e => { const p = at[e.src], q = at[e.dst]; make("line", { x1: p[0], y1: p[1], x2: q[0], y2: q[1], stroke: hue[e.kind], "stroke-width": 1 + 2 * e.support, "stroke-dasharray": dash[e.kind] }, `${e.src} ${e.kind} ${e.dst}: ${e.support}`); });
G.nodes.forEach(n => { const p = at[n.pid]; make("circle", { cx: p[0], cy: p[1], r: n.size / 2, fill: "#9bd" }, `${n.tree}: ${n.support}`); const t = make("text", { x: p[0], y: p[1], "font-size": 11, "text-anchor": "middle" }); t.textContent = n.numbered_tree; });
svg.onwheel = ev => { const k = ev.deltaY > 0 ? 1.1 : 0.9; box = [box[0] + box[2] * (1 - k) / 2, box[1] + box[3] * (1 - k) / 2, box[2] * k, box[3] * k]; show(); ev.preventDefault(); }; show();
</script></body></html>
"""


def write_html(nodes: DataFrame, edges: DataFrame, path: str) -> None:
    """A page of its own with the graph: hover for supports, wheel to zoom."""
    doc = graph_json(nodes, edges).first()["json"]
    with open(path, "w", encoding="utf-8") as f:
        f.write(PAGE % doc.replace("</", "<\\/"))


def span_forest(edges: DataFrame) -> DataFrame:
    """``pid, parent``: each pattern under the one that spans it with the highest support (ties by name)."""
    best = F.row_number().over(Window.partitionBy("src").orderBy(F.desc("support"), "dst"))
    return edges.where("kind = 'spans'").withColumn("r", best).where("r = 1").select(F.col("src").alias("pid"), F.col("dst").alias("parent"))

