"""Evaluation and maintenance of view trees."""

from __future__ import annotations

from collections.abc import Iterable, Mapping, Sequence
from dataclasses import dataclass, field

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.functions.rings import IntRing, LongRing
from ringview.operators.relation import AT, COUNT, SIGN, KeyedRelation, aggregate, indicator, indicator_difference, join, join_as_of, marginalize, support, support_change, union
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.viewtree import Leaf, Node, ViewTree, add_indicators, build_free_top_tree, build_tree, materialized, path_to
from ringview.plans.varorder import VariableOrder, best_order, canonical_order, fd_order, free_top_order
from ringview.sources.store import ViewStore

Database = Mapping[str, DataFrame]


def leaf_relation(leaf: Leaf, bag: DataFrame, q: NaturalJoinQuery) -> KeyedRelation:
    if leaf.onto is not None:
        return indicator(KeyedRelation.from_bag(bag, leaf.schema, IntRing()), leaf.onto, q.ring)
    return KeyedRelation.from_bag(bag, leaf.schema, q.ring)


def view(node: Node, inputs: list[KeyedRelation]) -> KeyedRelation:
    """Join of the inputs in order, then sums."""
    rel = inputs[0]
    for other in inputs[1:]:
        rel = join(rel, other, total=False)
    return summed(node, rel, len(inputs))


def summed(node: Node, rel: KeyedRelation, joined: int = 2) -> KeyedRelation:
    """A view from the join of its inputs; numbers of batches stay."""
    keys = (*node.keys, AT) if AT in rel.keys else node.keys
    counted = [v for v in rel.keys if v in node.counted]
    if counted:
        rel = marginalize(rel, counted, lifted=False)
    gone = [v for v in rel.keys if v not in keys and v not in node.counted]
    if gone:
        rel = marginalize(rel, gone)
    elif isinstance(rel.ring, LongRing) and not counted and joined > 1:
        rel = union(KeyedRelation(rel.df.select(*keys, *[c for c in rel.df.columns if c not in rel.keys]), keys, rel.ring))
    elif joined > 1 or rel.keys != keys:
        rel = KeyedRelation(rel.df.select(*keys, *[c for c in rel.df.columns if c not in rel.keys]), keys, rel.ring)
    return rel


def from_leaf(node: Node, bag: DataFrame, q: NaturalJoinQuery) -> KeyedRelation:
    """A view over one relation, straight from its bag: one pass, columns that are not needed are never read."""
    gone = {v: F.col(v) for v in node.children[0].keys if v not in node.keys and v not in node.counted}
    bag = bag if SIGN in bag.columns else bag.withColumn(SIGN, F.lit(1))
    return aggregate(bag, (*node.keys, AT) if AT in bag.columns else node.keys, gone, q.ring)


def numbers(rel: KeyedRelation) -> KeyedRelation:
    """The same keys with their derivations as payloads (of a payload of rows, those of all rows: zero for the same keys)."""
    n = F.col(COUNT).cast("long")
    df = rel.df.groupBy(*rel.keys).agg(F.sum(n).alias("v")) if isinstance(rel.ring, LongRing) else rel.df.select(*rel.keys, n.alias("v"))
    return rel if rel.ring == IntRing() else KeyedRelation(df.withColumn(COUNT, F.col("v")), rel.keys, IntRing())


def content(tree: ViewTree, node: Node | Leaf, db: Database, seen: dict[str, KeyedRelation], counts: frozenset[str] = frozenset()) -> KeyedRelation:
    """A view from scratch; those named in ``counts`` carry multiplicities only."""
    if node.name not in seen:
        if node.name in counts:
            seen[node.name] = view(node, [numbers(content(tree, c, db, seen, counts)) for c in node.children])
        elif isinstance(node, Leaf):
            seen[node.name] = leaf_relation(node, db[node.relation], tree.query)
        elif len(node.children) == 1 and isinstance(node.children[0], Leaf) and node.children[0].onto is None:
            seen[node.name] = from_leaf(node, db[node.children[0].relation], tree.query)
        else:
            seen[node.name] = view(node, [content(tree, c, db, seen, counts) for c in node.children])
    return seen[node.name]


def evaluate(tree: ViewTree, db: Database) -> KeyedRelation:
    """The result from scratch, bottom-up; trees of a forest are multiplied."""
    seen: dict[str, KeyedRelation] = {}
    out = content(tree, tree.roots[0], db, seen)
    for r in tree.roots[1:]:
        out = join(out, content(tree, r, db, seen))
    return out


def frontier(tree: ViewTree) -> list[Node | Leaf]:
    """The lowest views over free variables only; the result is their product."""
    free, out = set(tree.query.free), []

    def at(n: Node | Leaf) -> None:
        kids = n.children if isinstance(n, Node) else ()
        if set(n.keys) <= free and not (kids and all(set(c.keys) <= free for c in kids)):
            out.append(n)
        else:
            for c in kids:
                at(c)

    for r in tree.roots:
        at(r)
    return out


def above_frontier(tree: ViewTree) -> frozenset[str]:
    """Views over free variables that stand above others of this kind."""
    low = {n.name for n in frontier(tree)}

    def at(n: Node | Leaf) -> tuple[bool, set[str]]:
        if n.name in low or isinstance(n, Leaf):
            return n.name in low, set()
        below = [at(c) for c in n.children]
        found = any(f for f, _ in below)
        return found, set().union(*(a for _, a in below)) | ({n.name} if found else set())

    return frozenset().union(*(at(r)[1] for r in tree.roots))


@dataclass
class Engine:
    """Keeps a query's result, or its factorized form, up to date.

    ``free_top``: views for enumeration.  ``indicators``: projections on cycles.  ``updatable``: relations that change
    (all but static ones, if not given).  ``keep_base``: base relations are stored too.  ``place``: relations that hang
    below a lower variable than their own lowest.  ``same``: a relation symbol and the relations that are its copies under
    other variable names; a change of the symbol is applied to one after another.  ``count_only_above``: for enumeration,
    views above those that give a tuple its payload keep multiplicities only, which says whether a tuple is still there.
    ``by_difference``: changes of an indicator are the difference of its content before and after, computed whole; a
    contrast to the counts of supports, which read touched tuples only.
    """

    query: NaturalJoinQuery
    order: VariableOrder | None = None
    updatable: Iterable[str] | None = None
    free_top: bool = False
    indicators: bool = False
    keep_base: bool = False
    store: ViewStore | None = None
    place: Mapping[str, str] = field(default_factory=dict)
    same: Mapping[str, Sequence[str]] = field(default_factory=dict)
    count_only_above: bool = False
    by_difference: bool = False
    tree: ViewTree = field(init=False)
    stored: set[str] = field(init=False)
    counts: frozenset[str] = field(init=False, default=frozenset())

    def __post_init__(self) -> None:
        q = self.query
        if self.order is None:
            self.order = choose_order(q, self.free_top)
        self.tree = build_free_top_tree(q, self.order) if self.free_top else build_tree(q, self.order, self.place)
        if self.indicators:
            self.tree = add_indicators(self.tree)
        self.updates = [r for r in q.relations if r not in q.static] if self.updatable is None else list(self.updatable)
        self.stored = materialized(self.tree, self.updates)
        if self.free_top:
            self.stored |= {n.name for n in frontier(self.tree)}
        self.store = self.store or ViewStore(q.ring)
        self._bases = {x.relation for x in self.tree.leaves() if x.onto is not None} | (set(q.relations) if self.keep_base else set())
        if self.count_only_above:
            if not self.free_top:
                raise ValueError("payloads stay low in the tree for enumeration only (free_top)")
            self.counts = above_frontier(self.tree)
        self.store.rings |= {_base(r): IntRing() for r in self._bases} | {n: IntRing() for n in self.counts}
        if not self.free_top:
            self.store.only_read_last |= {r.name for r in self.tree.roots}
        #: Whether the store had the views already, from an earlier run.
        self.resumed = set(self.store.names()) >= self.stored | {_base(r) for r in self._bases}

    def load(self, db: Database) -> None:
        """Initial content; an empty table is fine."""
        seen: dict[str, KeyedRelation] = {}
        done: set[str] = set()

        def at(n: Node | Leaf) -> None:
            if isinstance(n, Node):
                for c in n.children:
                    at(c)
            if n.name in self.stored and n.name not in done:
                done.add(n.name)
                self.store.create(n.name, content(self.tree, n, db, seen, self.counts))
                seen[n.name] = self.store.read(n.name)

        for r in self.tree.roots:
            at(r)
        for r in sorted(self._bases):
            self.store.create(_base(r), KeyedRelation.from_bag(db[r], self.query.relations[r], IntRing()))
        self.store.commit()

    def _up(self, leaf: Leaf, delta: KeyedRelation | None, bag: DataFrame | None) -> None:
        """Push a change of a leaf to the root; each stored view on the way gets its delta."""
        below: Node | Leaf = leaf
        change = delta
        for n in path_to(self.tree, leaf):
            if below is leaf and leaf.name in self.stored:
                change = change or leaf_relation(leaf, bag, self.query)
                self.store.append(leaf.name, change)
            if change is None and len(n.children) == 1 and n.name not in self.counts:
                change = from_leaf(n, bag, self.query)
            else:
                change = self._step(n, below, change or leaf_relation(leaf, bag, self.query))
            if n.name in self.stored:
                self.store.append(n.name, change)
                change = self.store.latest(n.name)
            below = n

    def _step(self, n: Node, below: Node | Leaf, change: KeyedRelation) -> KeyedRelation:
        """The change of a view from that of one child and what it meets in the others."""
        inputs = [change if c is below else self.store.read_for(c.name, change) for c in n.children]
        return view(n, [numbers(x) for x in inputs] if n.name in self.counts else inputs)

    def apply(self, relation: str, delta: DataFrame, batch: tuple[str, int] | None = None) -> bool:
        """A signed bag of changes of one relation: its leaves first, then its indicators, so that each step sees the
        ones before.  With ``batch`` (a stream and its ascending batch number) a batch counts once, across restarts if the
        store is on disk; the answer is whether it counted now."""
        if batch and self.store.has(*batch):
            return False
        for copy in self.same.get(relation, [relation]):
            if copy not in self.updates:
                raise ValueError(f"{copy} is not updatable")
            self._apply(copy, delta if copy == relation else self._renamed(relation, copy, delta))
        self.store.commit(*(batch or ()))
        return True

    def apply_together(self, changes: Mapping[str, DataFrame], batch: tuple[str, int]) -> bool:
        """Batches of a stream that wait, in the same jobs: signed bags by relation, each row with the number of its batch
        (AT; a number belongs to one relation), and the stream with its last number.  Every batch keeps a change of its own
        in each view, against the other views as they were before that batch; numbers that the store has are passed over,
        the others are committed together."""
        stream, last = batch
        if self.store.has(stream, last):
            return False
        if self._bases or self.counts or self.same:
            raise ValueError("indicators, multiplicities above and copies of a symbol take one batch at a time")
        if set(changes) - set(self.updates):
            raise ValueError(f"{sorted(set(changes) - set(self.updates))} are not updatable")
        first = self.store.done.get(stream, -1) + 1
        bags = {r: (df if SIGN in df.columns else df.withColumn(SIGN, F.lit(1))).where((F.col(AT) >= first) & (F.col(AT) <= last)) for r, df in changes.items()}
        before = self.store.as_now()

        def at(n: Node | Leaf) -> KeyedRelation | None:
            if isinstance(n, Leaf):
                change = KeyedRelation.from_bag(bags[n.relation], (*n.schema, AT), self.query.ring) if n.relation in bags else None
            elif len(n.children) == 1 and isinstance(n.children[0], Leaf) and n.children[0].name not in self.stored:
                change = from_leaf(n, bags[n.children[0].relation], self.query) if n.children[0].relation in bags else None
            else:
                below = [at(c) for c in n.children]
                parts = [self._step_as_of(n, below, i, before, first, last) for i, c in enumerate(below) if c is not None]
                change = union(*parts) if len(parts) > 1 else parts[0] if parts else None
            if change is not None and n.name in self.stored:
                self.store.append(n.name, change)
                change = self.store.latest(n.name)
            return change

        for r in self.tree.roots:
            at(r)
        self.store.commit(stream, last)
        return True

    def _step_as_of(self, n: Node, below: list[KeyedRelation | None], i: int, before: ViewStore, first: int, last: int) -> KeyedRelation:
        """The numbered change of a view from that of its i-th child; the order of the factors is kept."""
        change = below[i]
        for j in [*range(i + 1, len(below)), *range(i - 1, -1, -1)]:
            change = join_as_of(change, before.read_for(n.children[j].name, below[i]), below[j], first, last, left=j < i)
        return summed(n, change, len(below))

    def _renamed(self, symbol: str, copy: str, delta: DataFrame) -> DataFrame:
        """Columns of a symbol's change, by place, under the names that a copy has."""
        keep = [c for c in delta.columns if c != SIGN]
        sign = [F.col(SIGN)] if SIGN in delta.columns else []
        return delta.select(*[F.col(c).alias(v) for c, v in zip(keep, self.query.relations[copy], strict=True)], *sign)

    def _apply(self, relation: str, delta: DataFrame) -> None:
        delta = delta if SIGN in delta.columns else delta.withColumn(SIGN, F.lit(1))
        for leaf in self.tree.leaves():
            if leaf.relation == relation and leaf.onto is None:
                self._up(leaf, None, delta)
        if relation not in self._bases:
            return
        # indicators change where the support of a projection leaves zero or returns to it: only touched tuples are read
        change = KeyedRelation.from_bag(delta, self.query.relations[relation], IntRing())
        old = self.store.read_for(_base(relation), change)
        keys = list(change.keys)
        before = KeyedRelation(old.df.join(change.df.select(*keys), keys, "left_semi"), change.keys, change.ring)
        after = union(before, change)
        entering, leaving = after.df.join(before.df, keys, "left_anti"), before.df.join(after.df, keys, "left_anti")
        pushed: set[str] = set()
        for leaf in self.tree.leaves():
            if leaf.relation == relation and leaf.onto is not None:
                onto = list(leaf.onto)
                whole = self.store.read(_base(relation))
                if self.by_difference:
                    moved = indicator_difference(whole, union(whole, change), onto)
                else:
                    near = KeyedRelation(whole.df.join(change.df.select(*onto).distinct(), onto, "left_semi"), whole.keys, whole.ring)
                    moved = support_change(support(near, onto), entering, leaving, onto)
                one = self.query.ring.unit() | self.query.ring.copies(F.col(SIGN).cast("long")) if isinstance(self.query.ring, LongRing) else self.query.ring.scale(self.query.ring.one(), F.col(SIGN))
                self._indicator(leaf, KeyedRelation(moved.select(*onto, *[c.alias(s) for s, c in one.items()], F.col(SIGN).cast("long").alias("__n")), leaf.onto, self.query.ring), pushed)
        self.store.append(_base(relation), change)

    def _indicator(self, leaf: Leaf, change: KeyedRelation, pushed: set[str]) -> None:
        """Like any leaf; an indicator that stands at several places is stored once, with the first of them."""
        below: Node | Leaf = leaf
        delta = change
        if leaf.name in self.stored and leaf.name not in pushed:
            self.store.append(leaf.name, delta)
            pushed.add(leaf.name)
        for n in path_to(self.tree, leaf):
            delta = self._step(n, below, delta)
            if n.name in self.stored:
                self.store.append(n.name, delta)
                delta = self.store.latest(n.name)
            below = n

    def apply_batch(self, changes: Mapping[str, DataFrame]) -> None:
        for relation, delta in changes.items():
            self.apply(relation, delta)

    def result(self) -> KeyedRelation:
        """The maintained result; in factorized form it is enumerated."""
        if self.free_top:
            return self.enumerate_result()
        out = self.store.read(self.tree.roots[0].name)
        for r in self.tree.roots[1:]:
            out = join(out, self.store.read(r.name))
        return out

    def enumerate_result(self) -> KeyedRelation:
        """Top-down along the free variables: each source is joined on the variables bound so far and, as its keys all
        extend below, no partial row is lost again; payloads of the lowest free views are multiplied on the way."""
        q = self.query
        low = {n.name: n for n in frontier(self.tree)}
        out: KeyedRelation | None = None
        used: set[str] = set()
        for name in self.tree.sources:
            rel = self.store.read(name)
            if name not in low:
                keys = tuple(k for k in rel.keys if k in q.free)
                if out is not None and set(keys) <= set(out.keys):
                    continue
                rel = indicator(rel, keys, q.ring)
            used.add(name)
            out = rel if out is None else join(out, rel)
        for name in low:
            if name not in used:
                rel = self.store.read(name)
                out = rel if out is None else join(out, rel)
        assert out is not None
        order = tuple(v for v in q.variables if v in out.keys)
        return KeyedRelation(out.df.select(*order, *[c for c in out.df.columns if c not in out.keys]), order, out.ring)

    def payload_of(self, **values: object) -> DataFrame:
        """Payload of one tuple of the result: a lookup in each of the lowest free views."""
        out: KeyedRelation | None = None
        for n in frontier(self.tree):
            rel = self.store.read(n.name)
            rel = KeyedRelation(rel.slice(**{k: values[k] for k in rel.keys}), rel.keys, rel.ring)
            out = rel if out is None else join(out, rel)
        assert out is not None
        return out.df

    def view_count(self) -> int:
        return len(self.stored)

    def view_sizes(self) -> dict[str, int]:
        return {n: self.store.read(n).size() for n in sorted(self.stored)}


def _base(relation: str) -> str:
    return f"base_{relation}"


def choose_order(q: NaturalJoinQuery, free_top: bool) -> VariableOrder:
    """The best class that the query has: canonical, by dependencies, free-top, else by cost."""
    for method in (canonical_order, fd_order) if q.fds or free_top else ():
        try:
            order = method(q)
            if order.is_free_top(q.free):
                return order
        except ValueError:
            continue
    return free_top_order(q) if free_top else best_order(q)
