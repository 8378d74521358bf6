"""Full conjunctive queries in three encodings: result keys, listing payloads, factorized payloads."""

from __future__ import annotations

from collections.abc import Sequence
from dataclasses import replace

from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from ringview.functions.rings import IntRing, RelationalRing
from ringview.operators.engine import Database, leaf_relation
from ringview.operators.relation import COUNT, KeyedRelation, join, marginalize
from ringview.plans.query import NaturalJoinQuery
from ringview.plans.varorder import VariableOrder
from ringview.plans.viewtree import Leaf, Node, ViewTree, path_to
from ringview.sources.store import ViewStore

KEYS, LIST_PAYLOAD, FACT_PAYLOAD = "keys", "listing payload", "factorized payload"


def keys_query(q: NaturalJoinQuery) -> NaturalJoinQuery:
    """The result in the keys, multiplicities as payload."""
    return replace(q, ring=IntRing())


def listing_query(q: NaturalJoinQuery) -> NaturalJoinQuery:
    """All keys summed away; the payload of the empty key is the result."""
    return replace(q, free=(), ring=RelationalRing(tuple(q.free)))


class Factorized:
    """The result as one small view for each variable: keys, the variable's values, multiplicities.

    Each view comes from the one below by a join and a sum, so the whole is never listed; a view's payload keeps its own
    variable only and the rest hangs below it by key.
    """

    def __init__(self, q: NaturalJoinQuery, order: VariableOrder, db: Database | None = None, store: ViewStore | None = None):
        self.q = replace(q, ring=IntRing(), free=())
        self.order = order
        self.free = tuple(q.free)
        self.tree = _plain_tree(self.q, order)
        self.store = store or ViewStore(self.q.ring)
        if db is not None:
            self._load(db)

    @property
    def views(self) -> dict[str, KeyedRelation]:
        return {x: self.store.read(f"own_{x}") for x in self.order.variables}

    def _own(self, n: Node, inputs: list[KeyedRelation]) -> KeyedRelation:
        """A node's join, counted by its keys and its own variable."""
        rel = inputs[0]
        for o in inputs[1:]:
            rel = join(rel, o)
        keys = (*n.keys, n.summed[0])
        own = marginalize(rel, [k for k in rel.keys if k not in keys], lifted=False)
        return KeyedRelation(own.df.select(*keys, "v", COUNT), keys, own.ring)

    def _input(self, c: Node | Leaf, change: KeyedRelation | None = None) -> KeyedRelation:
        """What a child hands up: a relation, or its variable's view summed over the variable."""
        name = c.name if isinstance(c, Leaf) else f"own_{c.summed[0]}"
        rel = self.store.read(name) if change is None else self.store.read_for(name, change)
        return rel if isinstance(c, Leaf) else marginalize(rel, c.summed, lifted=False)

    def _load(self, db: Database) -> None:
        def at(n: Node | Leaf) -> None:
            if isinstance(n, Leaf):
                self.store.create(n.name, leaf_relation(n, db[n.relation], self.q))
                return
            for c in n.children:
                at(c)
            self.store.create(f"own_{n.summed[0]}", self._own(n, [self._input(c) for c in n.children]))

        for r in self.tree.roots:
            at(r)

    def apply(self, relation: str, delta: DataFrame) -> None:
        """A signed bag of changes: every variable's view above the relation takes its part; nothing is listed."""
        leaf = next(x for x in self.tree.leaves() if x.relation == relation)
        change = leaf_relation(leaf, delta, self.q)
        self.store.append(leaf.name, change)
        below: Node | Leaf = leaf
        for n in path_to(self.tree, leaf):
            name = f"own_{n.summed[0]}"
            own = self._own(n, [change, *(self._input(c, change) for c in n.children if c is not below)])
            self.store.append(name, own)
            change = marginalize(self.store.latest(name), n.summed, lifted=False)
            below = n

    def expand(self) -> DataFrame:
        """Rows of the result over the free variables, with multiplicity ``v``, top-down."""
        out: DataFrame | None = None
        names = [x for x in self.order.variables if x in self.free]
        views = self.views
        for x in names:
            v = views[x]
            keys = v.df.select(*v.keys)
            out = keys if out is None else out.join(keys, [k for k in v.keys if k in out.columns]) if set(v.keys) & set(out.columns) else out.crossJoin(keys)
        assert out is not None
        for x in names:
            below = [c for c in self.order.children(x) if c in self.free]
            if not below:
                v = self.views[x]
                leaf = v.df.select(*v.keys, F.col("v").alias(f"__{x}"))
                out = out.join(leaf, list(v.keys))
        marks = [c for c in out.columns if c.startswith("__")]
        product = F.lit(1).cast("long")
        for m in marks:
            product = product * F.col(m)
        inner = [x for x in names if any(c in self.free for c in self.order.children(x))]
        rest = [r for r in self.q.relations if self.order.place(self.q, r) in inner]
        if rest or any(c not in self.free for x in inner for c in self.order.children(x)):
            product = None  # multiplicities of inner branches: divide the view's total by its free branches' totals
        if product is None:
            return self._expand_weighted(out.select(*names), names)
        return out.select(*names, product.alias("v"))

    def _expand_weighted(self, rows: DataFrame, names: Sequence[str]) -> DataFrame:
        """With bound branches or relations at inner variables: what a view counts beyond its free branches."""
        weight = F.lit(1).cast("long")
        for x in names:
            v = self.views[x]
            rows = rows.join(v.df.select(*v.keys, F.col("v").alias(f"__t_{x}")), list(v.keys))
            part = F.col(f"__t_{x}")
            for c in (c for c in self.order.children(x) if c in self.free):
                low = self.views[c]
                keys = [k for k in low.keys if k != c]
                total = low.df.groupBy(*keys).agg(F.sum("v").alias(f"__b_{c}")) if keys else low.df.agg(F.sum("v").alias(f"__b_{c}"))
                rows = rows.join(total, keys) if keys else rows.crossJoin(total)
                part = part / F.col(f"__b_{c}")
            weight = weight * part
        return rows.select(*names, F.round(weight).cast("long").alias("v"))

    def aggregate(self, var: str | None = None) -> int:
        """COUNT of the result, or SUM of a variable, from the factorized form in one pass."""
        if var is None:
            top = [self.views[r] for r in self.order.roots]
            out = 1
            for v in top:
                out *= v.df.agg(F.sum("v")).first()[0] or 0
            return out
        path = [*self.order.ancestors(var), var]
        rows: DataFrame | None = None
        for x in path:
            v = self.views[x]
            own = v.df.select(*v.keys, F.col("v").alias(f"__t_{x}"))
            rows = own if rows is None else rows.join(own, [k for k in v.keys if k in rows.columns]) if set(v.keys) & set(rows.columns) else rows.crossJoin(own)
            if x != var:
                nxt = path[path.index(x) + 1]
                low = self.views[nxt]
                keys = [k for k in low.keys if k != nxt]
                total = low.df.groupBy(*keys).agg(F.sum("v").alias(f"__b_{nxt}")) if keys else low.df.agg(F.sum("v").alias(f"__b_{nxt}"))
                rows = rows.join(total, keys) if keys else rows.crossJoin(total)
        assert rows is not None
        weight = F.col(f"__t_{var}").cast("double")
        for x in path[:-1]:
            nxt = path[path.index(x) + 1]
            weight = weight * F.col(f"__t_{x}") / F.col(f"__b_{nxt}")
        return int(round(rows.agg(F.sum(F.col(var) * weight)).first()[0] or 0))

    def with_free(self, free: Sequence[str]) -> Factorized:
        """The same views for fewer free variables."""
        out = Factorized(replace(self.q, free=tuple(free)), self.order)
        out.store = self.store
        return out

    def size(self) -> int:
        """Values stored: one for each row of a variable's view, none for its keys."""
        return sum(self.views[x].size() for x in self.free)


def _plain_tree(q: NaturalJoinQuery, order: VariableOrder):
    def at(x: str) -> Node:
        kids: list[Node | Leaf] = [at(c) for c in order.children(x)]
        kids += [Leaf(r, s) for r, s in q.relations.items() if order.place(q, r) == x]
        return Node(f"F_{x}", order.dep(q, x), tuple(kids), (x,))

    return ViewTree(q, order, tuple(at(r) for r in order.roots))


def listing_size(rows: DataFrame, free: Sequence[str]) -> int:
    return rows.count() * len(free)
