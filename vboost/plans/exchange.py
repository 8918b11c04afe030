"""Growing trees through ciphers: what each party holds, and every message between them.

Each party has a frame of its own bins by instance. The active party encrypts the sampled rows' gradients once a tree;
in each layer a passive party folds cipher cells for the smaller children, takes the siblings by homomorphic
subtraction, and sends prefix sums under opaque ids; the active party opens them, names the best ids, and whoever owns a
split tells all parties where its rows go. A message is checked against what its receiver may see, written to the shared
folder, counted, and only then read by its receiver. Cipher operations are counted where they are made.

Frames that are joined by instance are bucketed by it, so that neither the bins nor the ciphers move between layers.
These joins are merges by hint: files of ciphers that repeat are far smaller than their rows, so that a choice by size
would send them to the driver to broadcast.
"""

from __future__ import annotations

import secrets
from collections.abc import Iterator

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

from ..he.base import Backend, Mock
from ..he.paillier import keygen
from ..operators import histogram
from ..sources.io import bucketed, cut, drop_bucketed
from . import protocol
from .params import FederatedSpec, Ledger, Params, Schedule, guard
from .tree import Node, Tree, best_local, gain_of, grid

ROW_BYTES = 12  # an instance id and a node


def backend(params: Params, seed: int | None = None) -> Backend:
    """The key pair that `he` names. A seed is for tests alone."""
    if params.he == "mock":
        return Mock(params.key_bits - 1)
    if params.he == "paillier":
        return keygen(params.key_bits, seed)
    raise ValueError(f"no ciphers under {params.he!r}")


class Federation:
    """The parties of one training run over aligned rows."""

    def __init__(self, binned: DataFrame, spec: FederatedSpec, params: Params, budget, ledger: Ledger, default_bins: list[int] | None = None, key: Backend | None = None, secret: str | None = None):
        self.spec, self.params, self.budget, self.ledger = spec, params, budget, ledger
        self.key = key or backend(params)
        self.public = self.key.public()
        if budget.slots < 1:
            raise ValueError(f"a key of {params.key_bits} bits holds no packed integer of {budget.b_gh} bits")
        self.secret = {p.name: secret or secrets.token_hex(16) for p in spec.parties}
        self.default_bins = default_bins
        self.active = spec.parties[0].name
        self.spark = binned.sparkSession
        self.frames = {}
        for p in spec.parties:
            first, end = spec.span(p.name)
            self.frames[p.name] = self._keep(binned.select("inst_id", F.slice("bins", first + 1, end - first).alias("bins")))

    def _keep(self, frame: DataFrame) -> DataFrame:
        return bucketed(frame, "inst_id")

    def close(self) -> None:
        for f in self.frames.values():
            drop_bucketed(f)

    def _send(self, tree: int, layer: int, sender: str, receivers: list[str], kind: str, frame: DataFrame, items: Column, size: int, private: tuple[str, ...] = (), **kinds: Column) -> DataFrame:
        """The message as its receivers read it. private: columns beside it that no receiver reads. kinds: what of the sender's work it counts."""
        for r in receivers:
            guard("active" if r == self.active else "passive", kind, [c for c in frame.columns if c not in private])
        kept = self._keep(frame) if "inst_id" in frame.columns else cut(frame)
        row = kept.agg(F.sum(items).alias("items"), *[F.sum(c).alias(k) for k, c in kinds.items()]).first()
        for r in receivers:
            self.ledger.send(tree, layer, sender, r, kind, row["items"] or 0, size)
        for k in kinds:
            self.ledger.send(tree, layer, sender, sender, k, row[k] or 0)
        return kept

    def _count(self, tree: int, layer: int, party: str, frame: DataFrame, **kinds: str) -> None:
        """Put sums of a frame's counters to the ledger: kind=column."""
        row = frame.agg(*[F.sum(c).alias(k) for k, c in kinds.items()]).first()
        for k in kinds:
            self.ledger.send(tree, layer, party, party, k, row[k] or 0)

    def grow(self, rows: DataFrame, plan: Schedule, tree: int, class_id: int = 0, classes: int = 1, allowed: list[int] | None = None) -> tuple[Tree, DataFrame]:
        """rows: inst_id, g, h of the sampled rows. Returns the tree, and inst_id, node of every aligned row's leaf."""
        p, spec, r = self.params, self.spec, self.params.precision_bits
        out = Tree(tree, class_id)
        passives = [x.name for x in spec.parties[1:] if any(x.name in plan.eligible(tree, layer) for layer in range(plan.depth))]
        fixed = histogram.fixed_columns(rows, r, classes, p.rounding).drop("g", "h")
        own = self._keep(fixed)
        held, enc = {}, None
        if passives:
            enc = self._send(tree, -1, self.active, passives, "enc_gh", protocol.encrypt_rows(rows, self.key, self.budget, p.packing, classes), F.size("c"), self.key.width, enc=F.size("c"))
            held = {name: self.frames[name].hint("merge").join(enc, "inst_id") for name in passives}
        names = [f"{n}{j}_{s}" for n in ("g", "h") for j in range(classes) for s in ("hi", "lo")]
        whole = own.agg(F.count("*").alias("cnt"), *[F.sum(c).alias(c) for c in names]).first()
        exact = lambda n, j: (whole[f"{n}{j}_hi"] or 0) * 2**32 + (whole[f"{n}{j}_lo"] or 0)
        sums = {0: (whole["cnt"], [exact("g", j) for j in range(classes)], [exact("h", j) for j in range(classes)])}
        place = self.frames[self.active].select("inst_id", F.lit(0).alias("node"))
        live_nodes, cells_before, grids_before, eligible_before, places = [0], {}, {}, None, []
        allowed_set = set(allowed) if allowed is not None else None
        packed = protocol.compressible(self.budget, p.packing, p.compress, classes, p.mo_compress)
        for layer in range(plan.depth):
            eligible = plan.eligible(tree, layer)
            small, sibling_of = live_nodes, {}
            if layer and p.subtract and eligible == eligible_before:
                small = []
                for a in sorted(n for n in live_nodes if n % 2 == 1):
                    x, y = (a, a + 1) if sums[a][0] <= sums[a + 1][0] else (a + 1, a)
                    small.append(x)
                    sibling_of[x] = y
            found: dict[int, dict] = {}
            if self.active in eligible:
                placed = own.hint("merge").join(self.frames[self.active], "inst_id").hint("merge").join(place.where(F.col("node").isin(*small)), "inst_id")
                grids = grid(histogram.limb_cells(placed, classes).toArrow(), p.max_bin, len(spec.parties[0].columns), classes)
                for x, y in sibling_of.items():
                    grids[y] = grids_before[(x - 1) // 2] - grids.get(x, 0)
                grids_before = grids
                for row in best_local(grids, r, p.reg_lambda, classes, p.min_child_rows, allowed_set):
                    found[row["node"]] = row | {"party": self.active}
            choices = {}
            for name in [x for x in eligible if x != self.active]:
                scored, infos, cells = self._passive_layer(name, held[name], place, small, sibling_of, cells_before.get(name), tree, layer, classes, packed, sums, allowed_set)
                cells_before[name] = cells
                for row in scored.groupBy("node").agg(F.max("gain").alias("gain")).collect():
                    if row["node"] not in found or row["gain"] > found[row["node"]]["gain"]:
                        found[row["node"]] = {"node": row["node"], "gain": row["gain"], "party": name}
                choices[name] = (scored, infos)
            for name, (scored, infos) in choices.items():
                mine = {n: x["gain"] for n, x in found.items() if x["party"] == name and x["gain"] > p.min_gain}
                if mine:
                    for node, x in self._choose(name, scored, infos, mine, tree, layer, classes).items():
                        found[node] |= x
            eligible_before = eligible
            after, owners = [], {}
            for node in sorted(live_nodes):
                cnt, g, h = sums[node]
                n = out.nodes.setdefault(node, self._node(node, cnt, g, h, r))
                x = found.get(node)
                if x is None or x["gain"] <= p.min_gain:
                    continue
                first = spec.span(x["party"])[0]
                n.fid, n.bin, n.gain = x["fid"] + first, x["bin"], x["gain"]
                left, right = 2 * node + 1, 2 * node + 2
                gl, hl = [x[f"g{j}_l"] for j in range(classes)], [x[f"h{j}_l"] for j in range(classes)]
                sums[left] = (x["cnt_l"], gl, hl)
                sums[right] = (cnt - x["cnt_l"], [a - b for a, b in zip(g, gl)], [a - b for a, b in zip(h, hl)])
                for child in (left, right):
                    out.nodes[child] = self._node(child, *sums[child], r)
                after += [left, right]
                owners.setdefault(x["party"], []).append((node, x["fid"], x["bin"]))
            if not after:
                break
            place = self._assign(place, owners, tree, layer)
            places.append(place)
            live_nodes = after
        drop_bucketed(own)
        if enc is not None:
            drop_bucketed(enc)
        for x in places[:-1]:
            drop_bucketed(x)
        return out, place

    @staticmethod
    def _node(node: int, cnt: int, g: list[int], h: list[int], r: int) -> Node:
        return Node(node, cnt, [float(x) / 2.0**r for x in g], [float(x) / 2.0**r for x in h])

    def _passive_layer(self, name, held, place, small, sibling_of, before, tree, layer, classes, packed, sums, allowed):
        """What the active party knows of a passive party's splits in a layer, the party's own table, and its cells."""
        p = self.params
        first, end = self.spec.span(name)
        defaults = self.default_bins[first:end] if p.sparse and self.default_bins else None
        live = held.hint("merge").join(place.where(F.col("node").isin(*small)), "inst_id").select("node", "bins", "c")
        cells = cut(protocol.cipher_histogram(live, self.public, defaults))
        self._count(tree, layer, name, cells.select("adds", "inversions", (F.col("cnt") * F.size("c")).alias("rows")), adds="adds", inversions="inversions", rows_folded="rows")
        if sibling_of:
            others = cut(protocol.cipher_subtract(before, cells, sibling_of, self.public))
            self._count(tree, layer, name, others, inversions="inversions")
            cells = cells.unionByName(others)
        usable = cells if allowed is None else cells.where(F.col("fid").isin(*[j - first for j in allowed if first <= j < end]))
        infos = cut(protocol.split_infos(usable, self.public, self.secret[name]))
        self._count(tree, layer, name, infos, prefix="adds")

        def send(frame: DataFrame) -> DataFrame:
            shifts = {"shifts": F.col("shifts")} if packed else {}
            return self._send(tree, layer, name, [self.active], "split_info", frame, F.lit(1) if packed else F.size("c"), self.key.width, ("shifts",), **shifts)

        opened = cut(protocol.exchange_infos(infos, self.key, self.budget, p.packing, packed, classes, send))
        self._count(tree, layer, self.active, opened, dec="dec")
        return self._gains(opened, sums, classes), infos, cells

    def _gains(self, opened: DataFrame, sums: dict, classes: int) -> DataFrame:
        """Adds gain, as the native grower computes it."""
        r, reg, least = self.params.precision_bits, self.params.reg_lambda, self.params.min_child_rows
        known = dict(sums)

        def run(frames: Iterator[pd.DataFrame]) -> Iterator[pd.DataFrame]:
            for f in frames:
                real = lambda column: np.array([[float(int(x)) for x in row] for row in column]).reshape(len(f), classes) / 2.0**r
                total = lambda k: np.array([[float(x) for x in known[n][k]] for n in f["node"]]).reshape(len(f), classes) / 2.0**r
                n = f["sample_count"].to_numpy()
                whole = np.array([known[x][0] for x in f["node"]], dtype=np.int64)
                gain = gain_of(real(f["g"]), real(f["h"]), total(1), total(2), reg)
                yield f.assign(gain=gain)[(n >= least) & (whole - n >= least)]

        return cut(opened.mapInPandas(run, protocol.SUMS + ", gain double"))

    def _choose(self, name, scored, infos, mine, tree, layer, classes) -> dict[int, dict]:
        """The passive party's own split and sums for each node; of equal gains it takes its first feature and bin."""
        gains = F.create_map(*[F.lit(x) for n, g in mine.items() for x in (n, g)])
        tied = scored.where(F.col("node").isin(*mine) & (F.col("gain") == gains[F.col("node")]))
        choice = self._send(tree, layer, self.active, [name], "split_choice", tied.select("split_uid", "node"), F.lit(1), 64)
        private = infos.select("split_uid", "fid", "bin").join(choice, "split_uid").groupBy("node").agg(F.min(F.struct("fid", "bin", "split_uid")).alias("x")).select("node", "x.*")
        chosen = self._send(tree, layer, name, [self.active], "chosen", private.select("split_uid", "node", "fid", "bin"), F.lit(1), 64, ("fid", "bin"))
        known = scored.join(chosen.select("split_uid"), "split_uid", "left_semi").select("node", "sample_count", "g", "h")
        out = {}
        for row in chosen.select("node", "fid", "bin").join(known, "node").collect():  # at most a layer's nodes
            out[row["node"]] = {"fid": row["fid"], "bin": row["bin"], "cnt_l": row["sample_count"]}
            out[row["node"]] |= {f"g{j}_l": int(row["g"][j]) for j in range(classes)} | {f"h{j}_l": int(row["h"][j]) for j in range(classes)}
        return out

    def _assign(self, place: DataFrame, owners: dict[str, list], tree: int, layer: int) -> DataFrame:
        """Where every row stands after a layer: each owner of splits tells the other parties."""
        names = [x.name for x in self.spec.parties]
        told = []
        for name, splits in owners.items():
            after = F.col("node")
            for node, fid, b in splits:
                after = F.when(F.col("node") == node, F.when(F.get("bins", F.lit(fid)) <= b, 2 * node + 1).otherwise(2 * node + 2)).otherwise(after)
            moved = self.frames[name].hint("merge").join(place.where(F.col("node").isin(*[n for n, _, _ in splits])), "inst_id").select("inst_id", after.cast("int").alias("node"))
            told.append(self._send(tree, layer, name, [x for x in names if x != name], "assign", moved, F.lit(1), ROW_BYTES))
        split_nodes = [n for s in owners.values() for n, _, _ in s]
        now = place.where(~F.col("node").isin(*split_nodes))
        for x in told:
            now = now.unionByName(x)
        kept = self._keep(now)
        for x in told:
            drop_bucketed(x)
        return kept
