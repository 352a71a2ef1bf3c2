"""Plain types of the engine: specifications, hash functions, trees, intervals, plans.

Everything here lives on the driver, is small, and round-trips through JSON.
"""

from __future__ import annotations

import json
from dataclasses import asdict, dataclass, field
from typing import Any

#: Attribute kinds and the hash families they get by default.
KINDS = ("text", "token_text", "code", "int", "float", "date", "timestamp")


@dataclass(frozen=True)
class Attribute:
    """A named attribute: a Spark SQL expression over the input, and the same for DuckDB where it differs."""

    name: str
    kind: str
    expr: str
    duck: str | None = None

    def __post_init__(self):
        if self.kind not in KINDS:
            raise ValueError(f"unknown attribute kind {self.kind}")

    @property
    def sql(self) -> str:
        return self.duck or self.expr


@dataclass(frozen=True)
class BlockingSpec:
    """What a task blocks: the id column and the attributes."""

    id_col: str
    attributes: tuple[Attribute, ...]

    def attribute(self, name: str) -> Attribute:
        for a in self.attributes:
            if a.name == name:
                return a
        raise KeyError(f"no attribute {name}")


@dataclass(frozen=True)
class BlockingConfig:
    """How to learn: the cap on a block and the choices of the learner.

    `min_shrink` under 1 bars functions whose largest child keeps more than that share of its
    node; `slack` learns with that share of the cap, to leave room for later growth. With
    `random_function` a node of a block tree may also choose the random split, which costs it
    the pairs that chance separates, where every function costs more; "best" tries both.
    """

    max_block_size: int
    scorer: str = "optimistic"
    max_rounds: int = 10
    max_depth: int = 12
    max_heavy_children: int = 10_000
    min_shrink: float = 1.0
    slack: float = 1.0
    seed: int = 42
    oversize: str = "split"
    random_function: bool = False

    @property
    def cap(self) -> int:
        return max(1, int(self.max_block_size * self.slack))


@dataclass(frozen=True)
class Interval:
    """Values from lo to hi of an ordered attribute; None is unbounded."""

    lo: Any
    hi: Any
    lo_incl: bool = True
    hi_incl: bool = False
    n: int = 0
    infeasible: bool = False


@dataclass(frozen=True)
class HashFn:
    """One atomic hash function, by family, attribute and parameters; `functions.hashes` turns it into an expression."""

    family: str
    attribute: str
    #: Plain values, tuples of them, or the intervals of a partition.
    params: tuple = ()

    @property
    def name(self) -> str:
        if self.family == "interval":
            return f"{self.attribute}.interval{len(self.params)}"
        if self.family == "interval_by":
            return f"{self.attribute}.interval{len(self.params) - 1}_by_{self.params[0]}"
        return ".".join([self.attribute, self.family + "".join(f"_{p}" for p in self.params)])


@dataclass
class Node:
    """A node of a tree: its function and its heavy children; every other value is a leaf of its own.

    A node without a function is a leaf that may be too large; it is split at random into `parts`.
    """

    id: int
    size: int
    pairs: int = 0
    hash: HashFn | None = None
    heavy: dict[str, "Node"] = field(default_factory=dict)
    parts: int = 1

    def walk(self):
        yield self
        for c in self.heavy.values():
            yield from c.walk()

    @property
    def height(self) -> int:
        """Levels of hash functions under and with this node."""
        return 0 if self.hash is None else 1 + max([c.height for c in self.heavy.values()], default=0)


@dataclass
class BlockTree:
    """A learnt disjoint blocking function. `chain` lists the functions of a conjunction, which a tree of nodes can't hold sparsely."""

    kind: str
    root: Node
    seed: int = 42
    chain: tuple[HashFn, ...] = ()
    #: For a chain: parts of the conjunctions (by their joined values) that are too large.
    chain_parts: dict[str, int] = field(default_factory=dict)

    @property
    def height(self) -> int:
        return len(self.chain) if self.chain else self.root.height

    @property
    def n_nodes(self) -> int:
        return sum(1 for _ in self.root.walk())

    def functions(self) -> list[HashFn]:
        found = {h.name: h for h in self.chain} | {n.hash.name: n.hash for n in self.root.walk() if n.hash}
        return [found[k] for k in sorted(found)]

    def to_json(self) -> str:
        return json.dumps({"kind": self.kind, "seed": self.seed, "root": _node_out(self.root), "chain": [_hash_out(h) for h in self.chain], "chain_parts": self.chain_parts}, default=str)

    @staticmethod
    def from_json(text: str) -> "BlockTree":
        d = json.loads(text)
        return BlockTree(d["kind"], _node_in(d["root"]), d["seed"], tuple(_hash_in(h) for h in d["chain"]), d["chain_parts"])


@dataclass
class RoundPlan:
    """Disjoint functions to be used one after the other, or at once; with the share of pairs each newly covered in training."""

    rounds: list[BlockTree]
    covered: list[int] = field(default_factory=list)

    def to_json(self) -> str:
        return json.dumps({"rounds": [t.to_json() for t in self.rounds], "covered": self.covered})

    @staticmethod
    def from_json(text: str) -> "RoundPlan":
        d = json.loads(text)
        return RoundPlan([BlockTree.from_json(t) for t in d["rounds"]], d["covered"])


def _hash_out(h: HashFn | None):
    if h is None:
        return None
    params = [asdict(p) | {"_interval": True} if isinstance(p, Interval) else p for p in h.params]
    return {"family": h.family, "attribute": h.attribute, "params": params}


def _hash_in(d) -> HashFn | None:
    if d is None:
        return None
    params = tuple(Interval(**{k: v for k, v in p.items() if k != "_interval"}) if isinstance(p, dict) else tuple(p) if isinstance(p, list) else p for p in d["params"])
    return HashFn(d["family"], d["attribute"], params)


def _node_out(n: Node):
    return {"id": n.id, "size": n.size, "pairs": n.pairs, "hash": _hash_out(n.hash), "parts": n.parts, "heavy": {v: _node_out(c) for v, c in n.heavy.items()}}


def _node_in(d) -> Node:
    return Node(d["id"], d["size"], d["pairs"], _hash_in(d["hash"]), {v: _node_in(c) for v, c in d["heavy"].items()}, d["parts"])
