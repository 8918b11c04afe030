"""Training parameters, parties and schedules."""

from __future__ import annotations

from collections.abc import Callable
from dataclasses import dataclass, field, replace

from ..functions.codec import Budget


@dataclass(frozen=True)
class Party:
    name: str
    role: str  # "active": features and label; "passive": features only
    columns: tuple[str, ...]


@dataclass(frozen=True)
class FederatedSpec:
    parties: tuple[Party, ...]

    def __post_init__(self) -> None:
        names = [c for p in self.parties for c in p.columns]
        if len(names) != len(set(names)):
            raise ValueError("parties must hold different features")
        if [p.role for p in self.parties].count("active") != 1 or self.parties[0].role != "active":
            raise ValueError("the first party, and no other, is active")

    @property
    def columns(self) -> list[str]:
        return [c for p in self.parties for c in p.columns]

    def span(self, party: str) -> tuple[int, int]:
        """First feature number of a party, and the number after its last."""
        at = 0
        for p in self.parties:
            if p.name == party:
                return at, at + len(p.columns)
            at += len(p.columns)
        raise KeyError(party)

    def owner(self, fid: int) -> str:
        return next(p.name for p in self.parties if self.span(p.name)[0] <= fid < self.span(p.name)[1])


@dataclass(frozen=True)
class Params:
    """Settings of a run.

    he: native sums without ciphers, "mock" (transparent integers through the whole exchange) or "paillier".
    grad_bound: largest |gradient| before sampling; above 1 for squared loss with wide labels. tight_h: hessians are at
    most a quarter (logistic and softmax). mo_compress: pack several vector infos in a cipher where they fit.
    subsample, colsample: shares of rows and features of a tree. party_order: whose tree comes when under mix.
    all_passives: under layered, all passives compete in the upper layers, not one for each tree.
    """

    trees: int = 25
    max_depth: int = 5
    max_bin: int = 32
    learning_rate: float = 0.3
    reg_lambda: float = 1.0
    min_gain: float = 0.0
    min_child_rows: int = 1
    objective: str = "logistic"
    classes: int = 1
    output: str = "single"
    mode: str = "joint"
    tree_per_party: int = 1
    h_active: int = 2
    h_passive: int = 3
    goss: tuple[float, float] | None = (0.2, 0.1)
    packing: bool = True
    compress: bool = True
    subtract: bool = True
    sparse: bool = False
    mo_compress: bool = True
    he: str = "native"
    key_bits: int = 1024
    precision_bits: int = 53
    rounding: str = "floor"
    tight_h: bool = False
    grad_bound: float = 1.0
    subsample: float = 1.0
    colsample: float = 1.0
    party_order: tuple[str, ...] | None = None
    all_passives: bool = False
    patience: int | None = None
    seed: int = 1
    binning: str = "approx_percentile"

    def but(self, **changes) -> "Params":
        return replace(self, **changes)

    def budget(self, rows: int) -> Budget:
        h_max = 0.25 if self.tight_h and self.objective != "squared" else 1.0
        b = Budget(rows, self.precision_bits, self.grad_bound, self.grad_bound, h_max, self.key_bits - 1, self.rounding)
        return b.amplified((1 - self.goss[0]) / self.goss[1]) if self.goss else b


@dataclass(frozen=True)
class Schedule:
    """Which parties may split at a layer of a tree."""

    eligible: Callable[[int, int], tuple[str, ...]]
    depth: int


def schedule(spec: FederatedSpec, params: Params) -> Schedule:
    """joint: all parties at every node. mix: whole trees of one party, the active first, then the passives in turn.
    layered: the first h_passive layers by one passive (rotating by tree) or by all of them, the h_active layers below
    by the active."""
    names = [p.name for p in spec.parties]
    if params.party_order and sorted(params.party_order) != sorted(names):
        raise ValueError("party_order must name every party once")
    passives = names[1:]
    if params.mode == "joint" or not passives:
        return Schedule(lambda tree, layer: tuple(names), params.max_depth)
    if params.mode == "mix":
        turn = params.party_order or names
        return Schedule(lambda tree, layer: (turn[tree // params.tree_per_party % len(turn)],), params.max_depth)
    if params.mode == "layered":
        upper = (lambda tree: tuple(passives)) if params.all_passives else lambda tree: (passives[tree % len(passives)],)
        pick = lambda tree, layer: upper(tree) if layer < params.h_passive else (names[0],)
        return Schedule(pick, params.h_passive + params.h_active)
    raise ValueError(params.mode)


@dataclass
class Ledger:
    """Counts and bytes of what the parties send each other."""

    rows: list[dict] = field(default_factory=list)

    def send(self, tree: int, layer: int, sender: str, receiver: str, kind: str, items: int, size: int = 0) -> None:
        self.rows.append({"tree": tree, "layer": layer, "sender": sender, "receiver": receiver, "kind": kind, "n_items": items, "n_bytes": items * size})

    def operations(self) -> dict[str, int]:
        """Counts of cipher operations under the names that costs.price knows.

        A run through ciphers counts each call; a native run has none and lists what a dense exchange would take.
        """
        return {k: self.items(k) for k in ("enc", "dec", "adds", "prefix", "shifts", "inversions")}

    def items(self, kind: str | None = None) -> int:
        return sum(r["n_items"] for r in self.rows if kind in (None, r["kind"]))


#: What each role may receive.
ALLOWED = {
    "passive": {"enc_gh": {"inst_id", "c"}, "assign": {"inst_id", "node"}, "split_choice": {"split_uid", "node"}, "totals": {"node", "cnt", "c"}},
    "active": {"split_info": {"split_uid", "node", "sample_count", "c", "pkg_id", "members"}, "assign": {"inst_id", "node"}, "chosen": {"split_uid", "node"}, "directions": {"inst_id", "bits"}},
}


def guard(role: str, kind: str, columns: list[str]) -> None:
    """Refuse a message whose columns the receiver must not see."""
    extra = set(columns) - ALLOWED[role].get(kind, set())
    if extra:
        raise PermissionError(f"{kind} to the {role} party holds {sorted(extra)}")
