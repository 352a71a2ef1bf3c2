"""Learners of disjoint blocking functions over the features of `sizes`.

All of them work on small arrays: signatures of the records and the labelled pairs. A
node is a set of signature rows and of pairs; splitting it by a function is a lookup.
"""

from __future__ import annotations

import math
from bisect import bisect_left
from dataclasses import dataclass, replace

import numpy as np

from ..model import BlockingConfig, BlockTree, Node
from .sizes import Features, pieces

SCORERS = ("optimistic", "pessimistic", "expected")
#: Kinds of pairs scored at once.
KINDS = 1 << 13


def elimination(scorer: str, broken: float, child_sizes: np.ndarray, child_pairs: np.ndarray, cap: int) -> float:
    """How many pairs a function costs its node: those it breaks, plus what its heavy children are feared to lose."""
    if scorer == "optimistic":
        return float(broken)
    if scorer == "pessimistic":
        return float(broken + child_pairs.sum())
    if scorer == "expected":
        parts = np.ceil(child_sizes / cap)
        return float(broken + (child_pairs * (parts - 1) / np.maximum(parts, 1)).sum())
    raise ValueError(f"unknown scorer {scorer}")


@dataclass
class Split:
    """What a function does to a node."""

    h: int
    score: float
    broken: int
    codes: np.ndarray
    sizes: np.ndarray
    pairs: np.ndarray
    progress: bool


@dataclass
class Scores:
    """What every function does to a node, one entry a function."""

    score: np.ndarray
    broken: np.ndarray
    n_heavy: np.ndarray
    largest: np.ndarray
    progress: np.ndarray


class _Flat:
    """Codes of all functions in one numbering, so that one count serves all functions of a node; for pairs, one row a kind."""

    def __init__(self, f: Features):
        width = np.array([len(v) + 1 for v in f.values])
        self.start = np.concatenate([[0], np.cumsum(width)[:-1]])
        self.n = int(width.sum())
        self.light = np.zeros(self.n, bool)
        self.light[self.start] = True
        self.pairs = f.pair_code.table + self.start[None].astype(np.int32)
        self.rank = np.argsort(np.argsort([h.name for h in f.library]))


def _flat(f: Features) -> _Flat:
    if not hasattr(f, "_flat"):
        f._flat = _Flat(f)
    return f._flat


def score_all(f: Features, sig: np.ndarray, prs: np.ndarray, cap: int, scorer: str, min_shrink: float = 1.0) -> Scores:
    """Score all functions at the node of signatures `sig` and pairs `prs`."""
    t = _flat(f)
    size = f.sizes(sig, t)
    kinds = f.pair_counts(prs)
    at = np.flatnonzero(kinds)
    pairs, kept = np.zeros(t.n), np.zeros(len(f.library), np.int64)
    for x in pieces(len(at), KINDS):
        same = f.same.table[at[x]] * kinds[at[x], None]
        pairs += np.bincount(t.pairs[at[x]].ravel(), same.ravel(), t.n)
        kept += same.sum(0)
    heavy = (size > cap) & ~t.light
    broken = (f.n_pairs(prs) - kept).astype(float)
    if scorer == "optimistic":
        score = broken
    elif scorer in ("pessimistic", "expected"):
        parts = np.ceil(size / cap)
        risk = pairs if scorer == "pessimistic" else pairs * (parts - 1) / np.maximum(parts, 1)
        score = broken + np.add.reduceat(np.where(heavy, risk, 0), t.start)
    else:
        raise ValueError(f"unknown scorer {scorer}")
    largest = np.maximum.reduceat(np.where(heavy, size, 0), t.start)
    total = f.total(sig)
    return Scores(score, broken, np.add.reduceat(heavy.astype(int), t.start), largest, (largest < total) & (largest <= min_shrink * total))


def split(f: Features, sig: np.ndarray, prs: np.ndarray, h: int, cap: int, scorer: str, min_shrink: float = 1.0) -> Split:
    """Score function h at a node, with its heavy children."""
    by = f.sizes_of(sig, h)
    heavy = np.flatnonzero(by[1:] > cap) + 1
    same = f.same[prs, h]
    pair_by = np.bincount(f.pair_code[prs, h], same if f.weight is None else same * f.weight[prs], len(f.values[h]) + 1)
    broken = f.n_pairs(prs[~same])
    total = f.total(sig)
    largest = by[heavy].max() if len(heavy) else 0
    return Split(h, elimination(scorer, broken, by[heavy], pair_by[heavy], cap), broken, heavy, by[heavy], pair_by[heavy], bool(largest < total) and bool(largest <= min_shrink * total))


def _inside(f: Features, prs: np.ndarray, h: int, codes: np.ndarray) -> list[np.ndarray]:
    """The pairs that share each of the heavy values `codes` of function h."""
    c = np.where(f.same[prs, h], f.pair_code[prs, h], 0)
    order = np.argsort(c, kind="stable")
    ends = c[order]
    return [prs[order[a:b]] for a, b in zip(np.searchsorted(ends, codes), np.searchsorted(ends, codes, "right"))]


def _pick(f: Features, score, n_heavy, largest, allowed) -> int | None:
    """The allowed function of least score: ties go to fewer heavy children, a smaller largest child, the name."""
    at = np.flatnonzero(allowed)
    if not len(at):
        return None
    return int(at[np.lexsort((_flat(f).rank[at], largest[at], n_heavy[at], np.round(score[at], 9)))[0]])


def best_split(f: Features, sig, prs, cap: int, config: BlockingConfig, used: frozenset = frozenset()) -> Split | None:
    """The eligible function that costs a node least."""
    s = score_all(f, sig, prs, cap, config.scorer, config.min_shrink)
    allowed = s.progress & (s.n_heavy <= config.max_heavy_children)
    allowed[list(used)] = False
    h = _pick(f, s.score, s.n_heavy, s.largest, allowed)
    return None if h is None else split(f, sig, prs, h, cap, config.scorer, config.min_shrink)


def _leaf(node: Node, cap: int) -> None:
    node.parts = max(1, int(np.ceil(node.size / cap)))


def _start(f: Features):
    return f.root(), np.arange(len(f.same))


def by_chance(node: Node, cap: int) -> float:
    """Pairs that a random split of the node is expected to separate."""
    return node.pairs * (1 - 1 / max(1, math.ceil(node.size / cap)))


def learn_block_tree(f: Features, config: BlockingConfig) -> BlockTree:
    """Only nodes over the cap get a function, each its own."""
    if config.scorer == "best":
        return best_of(f, config, learn_block_tree)
    cap, f = config.cap, f.by_kind()
    sig, prs = _start(f)
    root = Node(0, int(f.n), f.n_pairs(prs))
    todo, n = [(root, sig, prs, frozenset(), 0)], 1
    while todo:
        nxt = []
        for node, sig, prs, used, depth in todo:
            if node.size <= cap:
                continue
            s = best_split(f, sig, prs, cap, config, used) if depth < config.max_depth else None
            if s is None or config.random_function and by_chance(node, cap) < s.score:
                _leaf(node, cap)
                continue
            node.hash = f.library[s.h]
            for code, size, b in zip(s.codes, s.sizes, _inside(f, prs, s.h, s.codes)):
                a = f.child(sig, s.h, code)
                child = Node(n, int(size), f.n_pairs(b))
                n += 1
                node.heavy[f.values[s.h][code - 1]] = child
                nxt.append((child, a, b, used | {s.h}, depth + 1))
        todo = nxt
    return BlockTree("block_tree", root, config.seed)


def learn_level_tree(f: Features, config: BlockingConfig) -> BlockTree:
    """All nodes of a level over the cap share one function."""
    if config.scorer == "best":
        return best_of(f, config, learn_level_tree)
    cap, f = config.cap, f.by_kind()
    sig, prs = _start(f)
    root = Node(0, int(f.n), f.n_pairs(prs))
    level, n, used = [(root, sig, prs)] if root.size > cap else [], 1, set()
    for _ in range(config.max_depth):
        if not level:
            break
        every = [score_all(f, x, y, cap, config.scorer, config.min_shrink) for _, x, y in level]
        heavy = sum(x.n_heavy for x in every)
        allowed = np.any([x.progress for x in every], axis=0) & (heavy <= config.max_heavy_children)
        allowed[list(used)] = False
        h = _pick(f, sum(x.score for x in every), heavy, np.max([x.largest for x in every], axis=0), allowed)
        if h is None:
            break
        parts = [split(f, x, y, h, cap, config.scorer, config.min_shrink) for _, x, y in level]
        used.add(h)
        nxt = []
        for (node, a, b), s in zip(level, parts):
            node.hash = f.library[h]
            for code, size, cb in zip(s.codes, s.sizes, _inside(f, b, h, s.codes)):
                child = Node(n, int(size))
                n += 1
                node.heavy[f.values[h][code - 1]] = child
                ca = f.child(a, h, code)
                child.pairs = f.n_pairs(cb)
                nxt.append((child, ca, cb))
        level = nxt
    for node, _, _ in level:
        _leaf(node, cap)
    return BlockTree("level_tree", root, config.seed)


def learn_single(f: Features, config: BlockingConfig) -> BlockTree:
    """One function for all; what is still too large is split at random."""
    if config.scorer == "best":
        return best_of(f, config, learn_single)
    tree = learn_block_tree(f, replace(config, max_depth=1))
    tree.kind = "single"
    return tree


def learn_chain(f: Features, config: BlockingConfig) -> BlockTree:
    """A conjunction: every function splits every block, whatever its size.

    Functions are added while a block is too large. With oversize="split" the best prefix
    by training recall is kept, counting a pair in an oversized block by its chance to
    survive the random split; with "refine" all are kept.
    """
    if config.scorer == "best":
        return best_of(f, config, learn_chain)
    cap, f = config.cap, f.by_kind()
    sig, prs = _start(f)
    blocks: dict[tuple, tuple] = {(): (sig, prs)} if f.n > cap else {}
    together = prs
    chain: list[int] = []
    best: tuple | None = None
    while True:
        parts = {k: max(1, int(np.ceil(f.total(a) / cap))) for k, (a, _) in blocks.items()}
        alive = f.n_pairs(together) - sum(f.n_pairs(b) * (1 - 1 / parts[k]) for k, (_, b) in blocks.items())
        if best is None or alive > best[0] + 1e-9 or config.oversize == "refine":
            best = (alive, list(chain), parts)
        if not blocks or len(chain) >= config.max_depth:
            break
        every = [score_all(f, x, y, cap, config.scorer) for x, y in blocks.values()]
        heavy = sum(x.n_heavy for x in every)
        # pairs outside heavy blocks are split by the function as well
        broken = f.n_pairs(together) - f.kept(together)
        score = broken + sum(x.score - x.broken for x in every)
        allowed = np.any([x.progress for x in every], axis=0) & (heavy <= config.max_heavy_children)
        allowed[chain] = False
        h = _pick(f, score, heavy, np.max([x.largest for x in every], axis=0), allowed)
        if h is None:
            break
        s = [split(f, x, y, h, cap, config.scorer) for x, y in blocks.values()]
        nxt = {}
        for (k, (a, b)), x in zip(blocks.items(), s):
            for code, inside in zip(x.codes, _inside(f, b, h, x.codes)):
                nxt[k + (f.values[h][code - 1],)] = (f.child(a, h, code), inside)
        blocks = nxt
        together = together[f.same[together, h]]
        chain.append(h)
    _, kept, parts = best
    root = Node(0, int(f.n), f.n_pairs(prs))
    if not kept:
        root.parts = parts.get((), 1)
    return BlockTree("chain", root, config.seed, tuple(f.library[h] for h in kept), {"\x1f".join(k): p for k, p in parts.items() if k})


def exhaustive_tree(f: Features, config: BlockingConfig, depth: int) -> BlockTree | None:
    """The block tree of at most `depth` levels that breaks fewest pairs, by trying every function at every node; None where no tree keeps the cap.

    Exponential in depth, for few functions: finding the best tree is NP-hard.
    """
    cap = config.cap

    def best(sig, prs, left: int, used: frozenset) -> tuple[int, Node] | None:
        node = Node(0, int(f.total(sig)), len(prs))
        if f.total(sig) <= cap:
            return 0, node
        found: tuple[int, Node] | None = None
        for h in range(len(f.library)) if left else ():
            if h in used:
                continue
            s = split(f, sig, prs, h, cap, "optimistic")
            lost, kids = s.broken, {}
            for code in s.codes:
                if found is not None and lost >= found[0]:
                    break
                sub = best(f.child(sig, h, code), prs[f.same[prs, h] & (f.pair_code[prs, h] == code)], left - 1, used | {h})
                if sub is None:
                    break
                lost += sub[0]
                kids[f.values[h][code - 1]] = sub[1]
            if len(kids) == len(s.codes) and (found is None or lost < found[0]):
                found = lost, Node(0, node.size, node.pairs, f.library[h], kids)
        return found

    got = best(*_start(f), depth, frozenset())
    if got is None:
        return None
    level, n = [got[1]], 0
    while level:
        for node in level:
            node.id, n = n, n + 1
        level = [c for node in level for c in node.heavy.values()]
    return BlockTree("block_tree", got[1], config.seed)


def best_of(f: Features, config: BlockingConfig, learner) -> BlockTree:
    """Learn with every scorer (block trees also with the random split as a function) and keep the tree of best training recall; ties go to the scorer named first."""
    chance = (False, True) if learner is learn_block_tree else (False,)
    trees = [learner(f, replace(config, scorer=s, random_function=r)) for s in SCORERS for r in chance]
    return max(trees, key=lambda t: hits(f, t))


LEARNERS = {"single": learn_single, "chain": learn_chain, "level_tree": learn_level_tree, "block_tree": learn_block_tree}


def _shared(f: Features, rows: np.ndarray, h: int, v: str) -> np.ndarray:
    """Whether pairs that function h keeps share its value v: by the number of a heavy value, else by the value itself."""
    i = bisect_left(f.values[h], v)
    if i < len(f.values[h]) and f.values[h][i] == v:
        return f.pair_code[rows, h] == i + 1
    return f.same_light(rows, h, v)


def _parts(f: Features, tree: BlockTree) -> np.ndarray:
    """For each row of `f` what becomes of its pairs: 0 they are broken, 1 kept, more the random parts of the block they share."""
    at = {h.name: i for i, h in enumerate(f.library)}
    n = len(f.same)
    out = np.ones(n, np.int32)
    if tree.chain:
        cols = [at[h.name] for h in tree.chain]
        out[~f.same[:, cols].all(1)] = 0
        for k, p in tree.chain_parts.items():
            rows = np.flatnonzero(out)
            for h, v in zip(cols, k.split("\x1f")):
                rows = rows[_shared(f, rows, h, v)]
            out[rows] = p
        return out
    todo = [(tree.root, np.arange(n))]
    while todo:
        node, rows = todo.pop()
        if node.hash is None:
            if node.parts > 1:
                out[rows] = node.parts
            continue
        h = at[node.hash.name]
        out[rows[~f.same[rows, h]]] = 0
        rows = rows[f.same[rows, h]]
        for v, child in node.heavy.items():
            todo.append((child, rows[_shared(f, rows, h, v)]))
    return out


def _known(f: Features, tree: BlockTree) -> bool:
    """Whether all values that the tree names are heavy here, so that pairs of a kind have the same block or none."""
    at, known = {h.name: i for i, h in enumerate(f.library)}, [set(v) for v in f.values]
    if tree.chain:
        return all(v in known[at[h.name]] for k in tree.chain_parts for h, v in zip(tree.chain, k.split("\x1f")))
    return all(v in known[at[n.hash.name]] for n in tree.root.walk() if n.hash for v in n.heavy)


def _fates(f: Features, tree: BlockTree):
    """(rows, what becomes of these pairs) of `f`, some at a time."""
    if _known(f, tree):
        g = f.by_kind()
        by = np.zeros(len(f.same.table), np.int32)
        by[g.same.kind] = _parts(g, tree)
        for x in pieces(len(f.same)):
            yield x, by[f.same.kind[x]]
    else:
        every = _parts(f, tree)
        for x in pieces(len(f.same)):
            yield x, every[x]


def covered(f: Features, tree: BlockTree) -> np.ndarray:
    """For each pair, whether the tree puts both records in one block, random splits included."""
    out = np.zeros(len(f.same), bool)
    for x, parts in _fates(f, tree):
        own = parts > 0
        at = np.flatnonzero(parts > 1)
        if len(at):
            m = f.mix[at + x.start] % parts[at, None].astype(np.int64)
            own[at] = m[:, 0] == m[:, 1]
        out[x] = own
    return out


def hits(f: Features, tree: BlockTree) -> int:
    """How many pairs are covered."""
    return int(covered(f, tree).sum())


def covered_by_any(f: Features, plan) -> np.ndarray:
    """Pairs that some round puts together."""
    out = np.zeros(len(f.same), bool)
    for t in plan.rounds:
        out |= covered(f, t)
    return out


def recall(f: Features, tree: BlockTree) -> float:
    return float(covered(f, tree).mean()) if len(f.same) else 1.0


# rounds -------------------------------------------------------------------------


def learn_rounds(f: Features, config: BlockingConfig, learner="block_tree"):
    """Overlapping blocking: learn, take away the pairs that are covered, learn again on the others.

    Ends when all are covered, a round covers nothing new, or after `max_rounds`. The
    learner may be "best_per_round": of all learners, the one that covers most.
    """
    from ..model import RoundPlan

    open_ = np.arange(len(f.same), dtype=np.int32)
    plan = RoundPlan([], [])
    while len(open_) and len(plan.rounds) < config.max_rounds:
        part = f.pick(open_)
        names = list(LEARNERS) if learner == "best_per_round" else [learner]
        trees = [LEARNERS[n](part, replace(config, seed=config.seed)) for n in names]
        found = [covered(part, t) for t in trees]
        i = int(np.argmax([x.sum() for x in found]))
        if not found[i].any():
            break
        plan.rounds.append(trees[i])
        plan.covered.append(int(found[i].sum()))
        open_ = open_[~found[i]]
    return plan


def covered_by_round(f: Features, plan) -> np.ndarray:
    """Pairs by rounds: whether the round puts the pair together."""
    return np.array([covered(f, t) for t in plan.rounds]).T.reshape(len(f.same), len(plan.rounds))
