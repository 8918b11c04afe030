"""Layer-wise growth and boosting on exact fixed-point sums.

The driver holds a tree's splits (at most 2^depth rows); a row's node is a CASE over its bins, so assigning rows to
nodes is a projection and no per-row state is kept between layers. A layer is one job: cells of the smaller children,
siblings by subtraction, prefix sums, gains, and the best split of each node. Where a layer has few cells (their
number depends on features, bins and depth, never on rows), they come to the driver and the rest is array arithmetic;
beyond LOCAL_CELLS all steps stay distributed. Both ways give the same splits.
"""

from __future__ import annotations

import time
from collections.abc import Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..functions import codec, metrics, objective
from ..operators import binning, chunks, histogram, sampling
from ..sources.io import cut, drop_bucketed, small_batches
from . import protocol
from .exchange import Federation
from .params import FederatedSpec, Ledger, Params, Schedule, guard, schedule
from .tree import Node, Tree, best_in_blocks, best_local, best_of_messages, grid

#: Cells of a layer that the driver takes at most (about 50 MB).
LOCAL_CELLS = 1 << 20


@dataclass
class Model:
    spec: FederatedSpec
    params: Params
    edges: list[list[float]]
    trees: list[Tree] = field(default_factory=list)
    history: list[dict] = field(default_factory=list)
    ledger: Ledger = field(default_factory=Ledger)

    @property
    def width(self) -> int:
        """Scores of a row."""
        return self.params.classes if self.params.classes > 1 else 1

    def scores(self, x: np.ndarray) -> np.ndarray:
        out = np.zeros((len(x), self.width))
        for t in self.trees:
            self._add_leaves(out, t, t.walk(x))
        return out

    def predict(self, df: DataFrame, keep: list[str]) -> DataFrame:
        """`keep` columns and score (array for classes): raw features are binned and walked in one Arrow pass."""
        binned = binning.apply(df, self.spec.columns, self.edges, keep)
        many = self.width > 1

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                x = batch.column("bins").values.to_numpy(zero_copy_only=False).reshape(batch.num_rows, -1) if batch.num_rows else np.zeros((0, len(self.edges)))
                s = self.scores(x)
                value = pa.array(list(s), pa.list_(pa.float64())) if many else pa.array(s[:, 0])
                yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in keep], value], names=[*keep, "score"])

        fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in binned.schema.fields if f.name in keep)
        return binned.mapInArrow(run, f"{fields}, score {'array<double>' if many else 'double'}")

    def score_packed(self, df: DataFrame) -> DataFrame:
        """y and score of the rows of chunks."""
        return chunks.scored(df, self.width, _adder(self.trees, self.params), self.edges, self.width > 1)

    def splits(self) -> list[tuple[int, int]]:
        """Tree and node of every split, in order."""
        return [(k, i) for k, t in enumerate(self.trees) for i in sorted(t.nodes) if t.nodes[i].fid is not None]

    def predict_federated(self, frames: dict[str, DataFrame], keep: tuple[str, ...] = (), ledger: Ledger | None = None) -> DataFrame:
        """inst_id, `keep` columns of the active party, and score, from each party's own frame: inst_id and its columns.

        A party tells the active one a bit for each split that it owns (does the row go right), one message of all
        trees; the active party, which holds the leaf weights, walks the trees. Rows that a party lacks are left out.
        """
        order, told = self.splits(), None
        for p in self.spec.parties:
            first, end = self.spec.span(p.name)
            mine = [(k, self.trees[t].nodes[i].fid - first, self.trees[t].nodes[i].bin) for k, (t, i) in enumerate(order) if first <= self.trees[t].nodes[i].fid < end]
            extra = list(keep) if told is None else []
            binned = binning.apply(frames[p.name], list(p.columns), self.edges[first:end], ["inst_id", *extra])
            fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in binned.schema.fields[:-1])
            bits = binned.mapInArrow(_directions(mine, len(order)), f"{fields}, bits binary")
            if told is None:
                told = bits
                continue
            guard("active", "directions", bits.columns)
            if ledger is not None:
                bits = cut(bits)
                ledger.send(-1, -1, p.name, self.spec.parties[0].name, "directions", bits.count(), -(-len(order) // 8) + 8)
            told = told.join(bits.withColumnRenamed("bits", "more"), "inst_id").withColumn("bits", F.concat("bits", "more")).drop("more")
        fields = ", ".join(f"{f.name} {f.dataType.simpleString()}" for f in told.schema.fields[:-1])
        kind = "array<double>" if self.width > 1 else "double"
        return told.mapInArrow(self._walk_told(order, len(self.spec.parties)), f"{fields}, score {kind}")

    def _walk_told(self, order: list[tuple[int, int]], parties: int):
        """Scores from the bits of all parties, one after the other."""
        column = {x: k for k, x in enumerate(order)}
        size = -(-len(order) // 8)

        def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
            for batch in batches:
                n = batch.num_rows
                raw = np.frombuffer(b"".join(batch.column("bits").to_pylist()), np.uint8).reshape(n, parties, size)
                right = np.unpackbits(np.bitwise_or.reduce(raw, axis=1), axis=1).astype(bool)
                out = np.zeros((n, self.width))
                for k, t in enumerate(self.trees):
                    leaf = np.zeros(n, dtype=np.int64)
                    for i in sorted(t.nodes):
                        if t.nodes[i].fid is not None:
                            here = leaf == i
                            leaf[here] = 2 * i + 1 + right[here, column[k, i]]
                    self._add_leaves(out, t, leaf)
                value = pa.array(list(out), pa.list_(pa.float64())) if self.width > 1 else pa.array(out[:, 0])
                rest = batch.schema.names[:-1]
                yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in rest], value], names=[*rest, "score"])

        return run

    def _add_leaves(self, out: np.ndarray, t: Tree, leaf: np.ndarray) -> None:
        for i, n in t.nodes.items():
            if n.fid is None:
                w = np.array(t.weight(i, self.params.reg_lambda)) * self.params.learning_rate
                columns = slice(None) if len(w) == self.width else t.class_id
                out[leaf == i, columns] += w

    def score_column(self, bins: str = "bins") -> Column:
        """The scalar score as one expression: for models of a few trees."""
        total = F.lit(0.0)
        for t in self.trees:
            total = total + t.leaf_column(lambda i, t=t: F.lit(t.weight(i, self.params.reg_lambda)[0] * self.params.learning_rate), bins)
        return total

    def node_rows(self) -> list[dict]:
        out = []
        for t in self.trees:
            for i, n in sorted(t.nodes.items()):
                out.append({"tree": t.tree, "class_id": t.class_id, "node": i, "party": self.spec.owner(n.fid) if n.fid is not None else None, "fid": n.fid, "bin": n.bin, "count": n.count, "gain": n.gain, "weight": t.weight(i, self.params.reg_lambda) if n.fid is None else None})
        return out


def _directions(mine: list[tuple[int, int, int]], splits: int):
    """The bits of a party's own splits (number, feature, bin) among all: set where a row goes right."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            flags = np.zeros((n, splits), dtype=bool)
            if mine and n:
                x = batch.column("bins").values.to_numpy(zero_copy_only=False).reshape(n, -1)
                for k, fid, b in mine:
                    flags[:, k] = x[:, fid] > b
            packed = np.packbits(flags, axis=1)
            rest = batch.schema.names[:-1]
            yield pa.RecordBatch.from_arrays([*[batch.column(c) for c in rest], pa.array([r.tobytes() for r in packed], pa.binary())], names=[*rest, "bits"])

    return run


def _smaller(out: Tree, layer_nodes: list[int]) -> tuple[list[int], dict[int, int]]:
    """The child with fewer rows of each pair, and its sibling."""
    sibling_of = {}
    for a in sorted(n for n in layer_nodes if n % 2 == 1):
        x, y = (a, a + 1) if out.nodes[a].count <= out.nodes[a + 1].count else (a + 1, a)
        sibling_of[x] = y
    return list(sibling_of), sibling_of


def _take(out: Tree, found: list[dict], classes: int, params: Params) -> list[int]:
    """Enter the best splits of a layer; the nodes of the next."""
    real = lambda sums: [[float(x) / 2.0**params.precision_bits for x in v] for v in sums]
    after = []
    for row in sorted(found, key=lambda x: x["node"]):
        whole, left = ([[int(row[f"{n}{j}_{s}"]) for j in range(classes)] for n in ("g", "h")] for s in ("t", "l"))
        n = out.nodes.setdefault(row["node"], Node(row["node"], row["cnt_t"], *real(whole)))
        if row["gain"] <= params.min_gain:
            continue
        n.fid, n.bin, n.gain = row["fid"], row["bin"], row["gain"]
        right = [[x - y for x, y in zip(a, b)] for a, b in zip(whole, left)]
        one, two = 2 * n.node + 1, 2 * n.node + 2
        out.nodes[one] = Node(one, row["cnt_l"], *real(left))
        out.nodes[two] = Node(two, row["cnt_t"] - row["cnt_l"], *real(right))
        after += [one, two]
    return after


def _list_layer(ledger: Ledger, spec: FederatedSpec, params: Params, plan: Schedule, out: Tree, tree: int, layer: int, layer_nodes: list[int], small: list[int], sibling_of: dict[int, int], classes: int, budget) -> None:
    """Enter what a dense exchange on ciphers would take for a layer."""
    per_row = budget.n_k(classes) if classes > 1 and budget else 1 if params.packing else 2
    for name in plan.eligible(tree, layer):
        if name == spec.parties[0].name:
            continue
        first, end = spec.span(name)
        splits = len(layer_nodes) * (end - first) * (params.max_bin - 1)
        infos = splits * per_row
        if budget and protocol.compressible(budget, params.packing, params.compress, classes, params.mo_compress):
            infos = len(layer_nodes) * -(-splits // len(layer_nodes) // budget.members(classes))
            ledger.send(tree, layer, name, name, "shifts", splits - infos)
        folded = sum(out.nodes[n].count for n in small if n in out.nodes)
        ledger.send(tree, layer, name, spec.parties[0].name, "split_info", infos, (2 * params.key_bits + 7) // 8)
        ledger.send(tree, layer, spec.parties[0].name, spec.parties[0].name, "dec", infos)
        ledger.send(tree, layer, name, name, "adds", folded * (end - first) * per_row)
        ledger.send(tree, layer, name, name, "prefix", splits * per_row)
        ledger.send(tree, layer, name, name, "inversions", len(sibling_of) * (end - first) * params.max_bin * per_row)


def _alone(rows: DataFrame, draws: list[sampling.Draw], edges: list[list[float]], k: int, classes: int, params: Params) -> Node:
    """The root of a tree that no cut can split: its count and sums."""
    n, sums = histogram.totals(rows, edges, draws[k], k, len(draws), classes, params.precision_bits, params.rounding)
    real = [v / 2.0**params.precision_bits for v in sums]
    return Node(0, n, real[:classes], real[classes:])


def grow_together(rows: DataFrame, draws: list[sampling.Draw], parts: int, edges: list[list[float]], spec: FederatedSpec, params: Params, plan: Schedule, jobs: dict[int, tuple[int, int]], classes: int, ledgers: dict[int, Ledger], budget, allowed: dict[int, list[int] | None]) -> dict[int, Tree]:
    """The trees of an epoch, which do not depend on each other, grown side by side: one job for each layer of all.

    rows: chunks of bins and of the gradients of the epoch's trees, in `parts` partitions. draws: their samples. jobs:
    place among those trees -> number and class of a tree. A layer's packed cells come to the driver if all partitions' cells are
    at most LOCAL_CELLS, and are else searched by block of features. Both give the same splits, and the same as `grow_tree`.
    """
    features, width = len(spec.columns), max(2, max(map(len, edges), default=0) + 1)
    priced = features * params.max_bin * 2**plan.depth * classes <= LOCAL_CELLS  # where the listed exchange subtracts
    trees = {k: Tree(*job) for k, job in jobs.items()}
    nodes, before, eligible_before = {k: [0] for k in jobs}, {}, {}
    for layer in range(plan.depth):
        pairs: dict[int, tuple[list[int], dict[int, int]]] = {}
        for k, layer_nodes in nodes.items():
            eligible = plan.eligible(trees[k].tree, layer)
            again = layer and params.subtract and priced and eligible == eligible_before[k]
            pairs[k] = _smaller(trees[k], layer_nodes) if again else (layer_nodes, {})
            eligible_before[k] = eligible
        direct = parts * features * width * classes * sum(map(len, nodes.values())) <= LOCAL_CELLS
        built = {k: pairs[k][0] if direct and (not layer or before) else nodes[k] for k in nodes}
        spans = {k: [spec.span(name) for name in eligible_before[k]] for k in nodes}
        slots = [(k, n) for k in nodes for n in built[k]]
        sent = histogram.cell_messages(rows, draws, edges, [(k, trees[k].walker(), built[k], spans[k]) for k in nodes], classes, width, params.precision_bits, params.rounding)
        mine = {k: None if allowed[k] is None else set(allowed[k]) for k in nodes}
        found: dict[int, list[dict]] = {k: [] for k in nodes}
        if direct:
            tables = {slots[s]: t for s, t in histogram.add_messages(sent.toArrow(), len(slots), features, width, classes).items()}
            for k in nodes:
                cells = {n: tables[k, n] for n in built[k] if (k, n) in tables}
                for x, y in pairs[k][1].items() if before else ():
                    cells[y] = before[k][(x - 1) // 2] - cells.get(x, 0)
                found[k] = best_local(cells, params.precision_bits, params.reg_lambda, classes, params.min_child_rows, mine[k])
                tables |= {(k, n): t for n, t in cells.items()}
            before = {k: {n: t for (j, n), t in tables.items() if j == k} for k in nodes}
        else:
            before = {}
            for x in best_of_messages(sent, [mine[k] for k, _ in slots], len(slots), features, width, params.precision_bits, params.reg_lambda, classes, params.min_child_rows):
                k, n = slots[x["node"]]
                found[k].append(x | {"node": n})
        after = {}
        for k, layer_nodes in nodes.items():
            after[k] = _take(trees[k], found[k], classes, params)
            _list_layer(ledgers[k], spec, params, plan, trees[k], trees[k].tree, layer, layer_nodes, *pairs[k], classes, budget)
        nodes = {k: v for k, v in after.items() if v}
        if not nodes:
            break
    for k, t in trees.items():
        if 0 not in t.nodes:  # no row, or no cut leaves rows on both sides
            t.nodes[0] = _alone(rows, draws, edges, k, classes, params)
    return trees


def _adder(trees: list[Tree], params: Params):
    """Adds the trees' leaf weights to the scores of a bin matrix."""
    step = Model(None, params, [], [Tree(t.tree, t.class_id, t.nodes) for t in trees])

    def add(out: np.ndarray, x: np.ndarray) -> None:
        for t in step.trees:
            step._add_leaves(out, t, t.walk(x))

    return add


def grow_tree(rows: DataFrame, spec: FederatedSpec, params: Params, plan: Schedule, tree: int, class_id: int = 0, classes: int = 1, ledger: Ledger | None = None, budget=None, allowed: list[int] | None = None, default_bins: list[int] | None = None) -> Tree:
    """rows: bins and limbs of the rows that the tree is grown on. allowed: features that may split; None is all.

    The ledger gets what a dense exchange on ciphers would take; nothing is encrypted here.
    """
    ledger = ledger if ledger is not None else Ledger()
    r = params.precision_bits
    out = Tree(tree, class_id)
    usual = (default_bins or [0] * len(spec.columns)) if params.sparse else None
    layer_nodes, cells_before, eligible_before = [0], None, None
    arrow = not params.sparse
    local = arrow and len(spec.columns) * params.max_bin * 2**plan.depth * classes <= LOCAL_CELLS
    width = max(64, params.max_bin)  # bins by plain arithmetic may number more than the quantiles'
    for layer in range(plan.depth):
        eligible = plan.eligible(tree, layer)
        small, sibling_of = layer_nodes, {}
        if layer and params.subtract and (local or not arrow) and cells_before is not None and eligible == eligible_before:
            small, sibling_of = _smaller(out, layer_nodes)
        spans = [spec.span(name) for name in eligible]
        if arrow:
            built = histogram.arrow_cells(rows, out.walker(), small, classes, spans, width)
            if allowed is not None:
                built = built.where(F.col("fid").isin(*allowed))
        else:
            node = out.node_column() if layer else F.lit(0)
            live = rows.withColumn("node", node.cast("int")).where(F.col("node").isin(*small))
            built = None
            for first, end in spans:
                part = histogram.build(live, classes, first, end - first, usual)
                built = part if built is None else built.unionByName(part)
        if local:
            cells = grid(built.toArrow(), params.max_bin, len(spec.columns), classes)
            for x, y in sibling_of.items():
                cells[y] = cells_before[(x - 1) // 2] - cells.get(x, 0)
            found = best_local(cells, r, params.reg_lambda, classes, params.min_child_rows, None if allowed is None else set(allowed))
        elif arrow:
            cells = None
            found = best_in_blocks(built, r, params.reg_lambda, classes, params.min_child_rows, params.max_bin)
        else:
            cells = built.unionByName(histogram.subtract(cells_before, built, sibling_of, classes)) if sibling_of else built
            cells = cells.persist()
            usable = cells if allowed is None else cells.where(F.col("fid").isin(*allowed))
            found = histogram.best(histogram.candidates(usable, r, params.reg_lambda, classes, params.min_child_rows)).collect()
            if cells_before is not None:
                cells_before.unpersist()
        cells_before, eligible_before = cells, eligible
        after = _take(out, found, classes, params)
        _list_layer(ledger, spec, params, plan, out, tree, layer, layer_nodes, small, sibling_of, classes, budget)
        layer_nodes = after
        if not after:
            break
    if 0 not in out.nodes:  # no row, or no cut leaves rows on both sides
        total = rows.agg(F.count("*").alias("cnt"), *[F.sum(f"{n}{j}_{p}").alias(f"{n}{j}_{p}") for n in ("g", "h") for j in range(classes) for p in ("hi", "lo")]).first()
        v = lambda n, j: ((total[f"{n}{j}_hi"] or 0) * 2**32 + (total[f"{n}{j}_lo"] or 0)) / 2.0**r
        out.nodes[0] = Node(0, total["cnt"], [v("g", j) for j in range(classes)], [v("h", j) for j in range(classes)])
    if cells_before is not None and not arrow:
        cells_before.unpersist()
    return out


def _advance_vectors(frame: DataFrame, trees: list[Tree], params: Params) -> DataFrame:
    """The same for vector scores, by array operations on Arrow batches: a CASE of vectors would compile for long."""
    step = Model(None, params, [], trees)
    walks = [(t, t.walker()) for t in trees]

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            n = batch.num_rows
            if not n:
                continue
            flat = lambda c: batch.column(c).values.to_numpy(zero_copy_only=False).reshape(n, -1)  # noqa: B023, E731
            x, out = flat("bins"), flat("score").copy()
            for t, walk in walks:
                step._add_leaves(out, t, walk(x))
            k = batch.schema.get_field_index("score")
            yield batch.set_column(k, batch.schema.field(k), pa.ListArray.from_arrays(pa.array(np.arange(n + 1, dtype=np.int32) * out.shape[1]), pa.array(out.ravel())))

    return frame.mapInArrow(run, frame.schema)


def _advance(frame: DataFrame, trees: list[Tree], params: Params, leaf_of: list[DataFrame] | None = None) -> DataFrame:
    """Adds the new trees' leaf weights to the scores. leaf_of: inst_id, node of each tree; by default from the bins."""
    if params.classes > 1 and leaf_of is None:
        return _advance_vectors(frame, trees, params)
    score = F.col("score")
    for k, t in enumerate(trees):
        weight = lambda i, t=t: [w * params.learning_rate for w in t.weight(i, params.reg_lambda)]

        def value(i: int, t=t, weight=weight) -> Column:
            w = weight(i)
            if params.classes == 1:
                return F.lit(w[0])
            return F.array(*[F.lit(x) for x in (w if len(w) == params.classes else [w[0] if j == t.class_id else 0.0 for j in range(params.classes)])])

        if leaf_of is None:
            added = t.leaf_column(value)
        else:
            frame = frame.hint("merge").join(leaf_of[k].withColumnRenamed("node", f"leaf{k}"), "inst_id")  # a row for each instance: never a broadcast
            leaves = [i for i, n in t.nodes.items() if n.fid is None]
            added = value(leaves[0])
            for i in leaves[1:]:
                added = F.when(F.col(f"leaf{k}") == i, value(i)).otherwise(added)
        score = score + added if params.classes == 1 else F.zip_with(score, added, lambda a, b: a + b)
    return frame.withColumn("score", score).drop(*[f"leaf{k}" for k in range(len(trees))] if leaf_of else [])


def usual_bins(binned: DataFrame, features: int) -> list[int]:
    """Each feature's most frequent bin, ties to the lower one: at most features x bins counts come to the driver's side."""
    counts = binned.select(F.posexplode("bins").alias("fid", "bin")).groupBy("fid", "bin").count()
    top = counts.groupBy("fid").agg(F.max_by("bin", F.struct("count", -F.col("bin"))).alias("bin"))
    found = {r["fid"]: r["bin"] for r in top.collect()}
    return [found.get(j, 0) for j in range(features)]


def _boost_packed(model: Model, frame: DataFrame, watched: DataFrame | None, evaluate: bool, cut_every: int, target: float | None) -> Model:
    """Native boosting over chunks. The trees of an epoch grow side by side, and scores are brought up by arrays."""
    spec, params, edges = model.spec, model.params, model.edges
    many = params.classes > 1
    kind = "softmax" if many else "squared" if params.objective == "squared" else "logistic"
    n = chunks.rows(frame)
    if n == 0:
        return model
    small_batches(frame.sparkSession)
    parts = frame._jdf.queryExecution().toRdd().getNumPartitions()
    budget, plan = params.budget(n), schedule(spec, params)
    classes = params.classes if many and params.output == "multi" else 1
    each = params.classes // classes if many else 1
    largest = 2 ** max(plan.depth - 1, 0) * len(spec.columns) * (params.max_bin + 1) * (1 + 4 * classes)
    # all trees of an epoch at once, but where a task has many rows no more than it can hold the sums of
    at_once = each if n <= parts * histogram.ROWS_AT_ONCE else max(1, histogram.HELD // largest)
    passive = lambda tree: any(p != spec.parties[0].name for layer in range(plan.depth) for p in plan.eligible(tree, layer))
    since: list[Tree] = []
    for epoch in range(params.trees):
        began = time.time()
        rows = chunks.gradients(frame, kind, model.width, _adder(since, params), edges).persist()
        numbers = [epoch * each + k for k in range(each)]
        draws = chunks.settle(rows, [sampling.Draw(params.seed + t, params.seed + 7 * t, params.subsample, params.goss) for t in numbers], edges)
        jobs = {k: (t, k) for k, t in enumerate(numbers)}
        allowed = {k: sampling.some_features(len(spec.columns), params.colsample, params.seed + t) if params.colsample < 1 else None for k, t in enumerate(numbers)}
        ledgers = {k: Ledger() for k in jobs}
        made: dict[int, Tree] = {}
        for at in range(0, each, at_once):
            some = {k: jobs[k] for k in range(at, min(each, at + at_once))}
            made |= grow_together(rows, draws, parts, edges, spec, params, plan, some, classes, ledgers, budget, allowed)
        rows.unpersist()
        grown = [made[k] for k in range(each)]
        for k, t in enumerate(grown):
            if passive(t.tree):
                items = t.nodes[0].count * (budget.n_k(classes) if classes > 1 else 1 if params.packing else 2)
                model.ledger.send(t.tree, -1, spec.parties[0].name, "passive", "enc_gh", items, (2 * params.key_bits + 7) // 8)
                model.ledger.send(t.tree, -1, spec.parties[0].name, spec.parties[0].name, "enc", items)
            model.ledger.rows += ledgers[k].rows
        model.trees += grown
        row = {"epoch": epoch, "trees": len(model.trees), "seconds": time.time() - began}
        since += grown
        if (epoch + 1) % cut_every == 0 and epoch + 1 < params.trees:
            frame, watched = (x if x is None else cut(chunks.advanced(x, model.width, _adder(since, params), edges)) for x in (frame, watched))
            parts, since = frame._jdf.queryExecution().toRdd().getNumPartitions(), []
        if evaluate:
            judged = chunks.scored(frame if watched is None else watched, model.width, _adder(since, params), edges, many)
            row["quality"] = metrics.accuracy(judged, metrics.argmax()).first()[0] if many else metrics.auc(judged).first()[0]
            row["loss"] = None if many else metrics.logloss(judged).first()[0]
        model.history.append(row)
        if _done(model, params, grown, evaluate, target):
            break
    return model


def _done(model: Model, params: Params, grown: list[Tree], evaluate: bool, target: float | None) -> bool:
    """No tree of the epoch has a split, the target is reached, or `patience` epochs brought nothing."""
    if all(t.nodes[0].fid is None for t in grown):
        return True
    if not evaluate:
        return False
    epoch, quality = len(model.history) - 1, model.history[-1]["quality"]
    if target is not None and quality >= target:
        return True
    return bool(params.patience and epoch >= params.patience and quality <= max(x["quality"] for x in model.history[: -params.patience]))


def train_packed(fit: DataFrame, test: DataFrame | None, spec: FederatedSpec, params: Params, edges: list[list[float]], evaluate: bool = False, target: float | None = None) -> Model:
    """`train` natively on rows that are binned already, as `chunks.of` gives them."""
    if params.he != "native" or params.sparse:
        raise ValueError("packed rows are for dense native runs")
    return _boost_packed(Model(spec, params, edges), fit, test, evaluate, 5, target)


def train(df: DataFrame, spec: FederatedSpec, params: Params, evaluate: bool = False, cut_every: int = 5, test: DataFrame | None = None, target: float | None = None, key=None, edges: list[list[float]] | None = None) -> Model:
    """Boosting over a frame with inst_id, y and all parties' columns (the simulated federation's aligned rows).

    Null labels are left out. With no rows the model has no trees. The columns of each party are binned alone; what
    a party sees of another's is what the ledger lists. With `he` other than native the whole exchange runs on ciphers
    (instances must be unique), and the ledger counts what was done; a native run lists a dense exchange's counts.

    evaluate: quality and loss of the training rows after each epoch; target: quality at which to stop; test: rows
    whose quality is measured instead. edges: bin edges fitted before, for several runs on the same rows.
    """
    edges = edges or binning.fit(df, spec.columns, params.max_bin, params.binning)
    model = Model(spec, params, edges)
    if params.he == "native" and not params.sparse:
        pack = lambda x: cut(chunks.of(x, spec.columns, edges))
        return _boost_packed(model, pack(df), None if test is None else pack(test), evaluate, cut_every, target)
    many = params.classes > 1
    start = F.array(*[F.lit(0.0)] * params.classes) if many else F.lit(0.0)
    binned = binning.apply(df.where("y IS NOT NULL"), spec.columns, edges, ["inst_id", "y"])
    frame = cut(binned.withColumn("score", start))
    n = frame.count()
    if n == 0:
        return model
    watched = None
    if test is not None:
        watched = cut(binning.apply(test.where("y IS NOT NULL"), spec.columns, edges, ["inst_id", "y"]).withColumn("score", start))
    usual = usual_bins(frame, len(spec.columns)) if params.sparse else None
    budget = params.budget(n)
    plan = schedule(spec, params)
    cipher = (2 * params.key_bits + 7) // 8
    fed = None
    if params.he != "native":
        fed = Federation(frame, spec, params, budget, model.ledger, usual, key)
        frame = frame.drop("bins")
    for epoch in range(params.trees):
        began = time.time()
        if many:
            grads = objective.softmax(frame, params.classes)
        else:
            grads = objective.squared(frame) if params.objective == "squared" else objective.logistic(frame)
        jobs = [(epoch, 0, params.classes)] if many and params.output == "multi" else [(epoch * params.classes + k, k, 1) for k in range(params.classes)] if many else [(epoch, 0, 1)]
        grown, places = [], []
        for tree, class_id, classes in jobs:
            one = grads
            if many and classes == 1:
                one = grads.withColumn("g", F.get("g", F.lit(class_id))).withColumn("h", F.get("h", F.lit(class_id)))
            if params.subsample < 1:
                one = sampling.uniform(one, params.subsample, params.seed + 7 * tree)
            if params.goss:
                one = sampling.goss(one, *params.goss, seed=params.seed + tree, norm="l1" if classes > 1 else "abs")
            allowed = sampling.some_features(len(spec.columns), params.colsample, params.seed + tree) if params.colsample < 1 else None
            if fed:
                t, place = fed.grow(cut(one.select("inst_id", "g", "h")), plan, tree, class_id, classes, allowed)
                grown.append(t)
                places.append(place)
                continue
            fixed = histogram.fixed_columns(one, params.precision_bits, classes, params.rounding).drop("g", "h", "score", "y").persist()
            if any(p != spec.parties[0].name for layer in range(plan.depth) for p in plan.eligible(tree, layer)):
                each = budget.n_k(classes) if classes > 1 else 1 if params.packing else 2
                kept = fixed.count()
                model.ledger.send(tree, -1, spec.parties[0].name, "passive", "enc_gh", kept * each, cipher)
                model.ledger.send(tree, -1, spec.parties[0].name, spec.parties[0].name, "enc", kept * each)
            grown.append(grow_tree(fixed, spec, params, plan, tree, class_id, classes, model.ledger, budget, allowed, usual))
            fixed.unpersist()
        model.trees += grown
        took = time.time() - began
        frame = _advance(frame, grown, params, places if fed else None)
        if fed or (epoch + 1) % cut_every == 0:
            frame = cut(frame)
        for x in places:
            drop_bucketed(x)
        row = {"epoch": epoch, "trees": len(model.trees), "seconds": took}
        if watched is not None:
            watched = _advance(watched, grown, params)
            if (epoch + 1) % cut_every == 0:
                watched = cut(watched)
        if evaluate:
            seen = frame if watched is None else watched
            row["quality"] = metrics.accuracy(seen, metrics.argmax()).first()[0] if many else metrics.auc(seen).first()[0]
            row["loss"] = None if many else metrics.logloss(seen).first()[0]
        model.history.append(row)
        if _done(model, params, grown, evaluate, target):
            break
    if fed:
        fed.close()
    return model
