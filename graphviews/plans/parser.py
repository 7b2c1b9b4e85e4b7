"""The query language: text to graph plan by recursive descent.

Clauses compose from left to right; each takes the relation of those before it.
MATCH, OPTIONAL MATCH, WHERE (conditions, label tests, patterns, negated patterns),
WITH and RETURN (DISTINCT, aggregates, ORDER BY, SKIP, LIMIT), UNWIND (AT a place, counted from 1).
"""

from __future__ import annotations

import re
from typing import Any

from graphviews.plans.expr import LABELS, TYPE, Agg, Call, Each, HasLabels, Lit, Op, Pattern, PlanError, Prop, Var, all_of, conjuncts, has_agg, parts, properties, replaced, variables
from graphviews.plans.ops import BOTH, IN, OUT, Anti, Distinct, Dual, Group, LeftOuter, NaturalJoin, Node, Project, ScanVertices, Select, Semi, SortTop, Unwind, Walk, WalkVar, kinds

_TOKEN = re.compile(r"""\s*(?:(?P<num>\d+\.\d+|\d+)|(?P<str>'(?:[^'\\]|\\.)*'|"(?:[^"\\]|\\.)*")|(?P<name>`[^`]+`|[A-Za-z_]\w*)|(?P<sym><>|<=|>=|->|<-|\.\.|[-+*/%=<>()\[\]{},.:|]))""")
_AGGREGATES = {"count", "sum", "avg", "min", "max", "stdev", "stdevp", "collect", "percentile"}
_CLAUSES = {"match", "optional", "where", "with", "return", "unwind", "order", "skip", "limit"}


def tokens(text: str) -> list[tuple[str, str]]:
    out, at, text = [], 0, text.rstrip()
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise PlanError(f"cannot read {text[at : at + 20]!r}")
        kind = m.lastgroup
        out.append((kind, m[kind].strip("`") if kind == "name" else m[kind]))
        at = m.end()
    return [*out, ("end", "")]


class Parser:
    def __init__(self, text: str, mode: str = "trail"):
        self.tokens, self.at, self.mode, self.made = tokens(text), 0, mode, 0
        self.plan: Node | None = None

    # -- tokens
    def peek(self, *words: str, ahead: int = 0) -> bool:
        kind, value = self.tokens[min(self.at + ahead, len(self.tokens) - 1)]
        return (value.lower() if kind == "name" else value) in words if kind != "str" else False

    def take(self, *words: str) -> bool:
        if self.peek(*words):
            self.at += 1
            return True
        return False

    def need(self, *words: str) -> str:
        value = self.tokens[self.at][1]
        if not self.take(*words):
            raise PlanError(f"expected {' or '.join(words)}, found {value!r}")
        return value

    def name(self) -> str:
        kind, value = self.tokens[self.at]
        if kind != "name":
            raise PlanError(f"expected a name, found {value!r}")
        self.at += 1
        return value

    def number(self) -> int:
        kind, value = self.tokens[self.at]
        if kind != "num" or "." in value:
            raise PlanError(f"expected a whole number, found {value!r}")
        self.at += 1
        return int(value)

    def fresh(self) -> str:
        self.made += 1
        return f"_{self.made}"

    # -- clauses
    def query(self) -> Node:
        while not self.peek(""):
            if self.take("match"):
                self.match()
            elif self.take("optional"):
                self.need("match")
                self.optional()
            elif self.take("unwind"):
                items = self.expression()
                self.need("as")
                name = self.name()
                place = self.name() if self.take("at") else None
                self.plan = Unwind(self.plan or Dual(), self.known(items), name, place)
            elif self.peek("with", "return"):
                final = self.need("with", "return").lower() == "return"
                self.result()
                if final:
                    if not self.peek(""):
                        raise PlanError(f"RETURN ends a query, found {self.tokens[self.at][1]!r}")
                    return self.plan
                if self.take("where"):
                    self.plan = self.filtered(self.plan, self.expression())
            else:
                raise PlanError(f"no clause begins with {self.tokens[self.at][1]!r}")
        raise PlanError("a query ends with RETURN")

    def match(self) -> None:
        plan = self.patterns(self.plan)
        self.plan = self.filtered(plan, self.expression()) if self.take("where") else plan

    def patterns(self, before: Node | None) -> Node:
        plan = before
        while True:
            one = self.pattern()
            self.no_mixed_kinds(plan, one)
            plan = NaturalJoin(plan, one) if plan is not None else one
            if not self.take(","):
                return plan

    @staticmethod
    def no_mixed_kinds(a: Node | None, b: Node) -> None:
        if a is not None:
            left = kinds(a)
            for n, k in kinds(b).items():
                if left.get(n, k) != k:
                    raise PlanError(f"{n} is both {left[n]} and {k}")

    def optional(self) -> None:
        right = self.patterns(None)
        left = self.plan or Dual()
        self.no_mixed_kinds(left, right)
        cond = self.expression() if self.take("where") else None
        if cond is not None:
            own, both = [], []
            for c in conjuncts(cond):
                if isinstance(c, Pattern) or any(isinstance(x, Pattern) for x in parts(c)):
                    right = self.filtered(right, c)
                else:
                    (own if variables(c) <= set(kinds(right)) - set(kinds(left)) else both).append(c)
            scope = {**kinds(left), **kinds(right)}
            for c in both:
                self.check(c, scope)
            right = self.filtered(right, all_of(own)) if own else right
            cond = all_of(both) if both else None
        self.plan = LeftOuter(left, right, cond)

    def node_pattern(self) -> tuple[str, tuple[str, ...], list[Any]]:
        self.need("(")
        var = self.name() if self.tokens[self.at][0] == "name" else self.fresh()
        labels = []
        while self.take(":"):
            labels.append(self.name())
        conditions = self.inline(var)
        self.need(")")
        return var, tuple(labels), conditions

    def inline(self, var: str) -> list[Any]:
        conditions = []
        if self.take("{"):
            while not self.take("}"):
                key = self.name()
                self.need(":")
                conditions.append(Op("=", (Prop(var, key), self.expression())))
                self.take(",")
        return conditions

    def pattern(self) -> Node:
        path = None
        if self.tokens[self.at][0] == "name" and self.peek("=", ahead=1):
            path = self.name()
            self.need("=")
        v, labels, conditions = self.node_pattern()
        plan: Node = ScanVertices(v, labels)
        seen, walked = {v}, 0
        while self.peek("-", "<-", "<"):
            back = self.take("<-") or (self.take("<") and bool(self.need("-")))
            if not back:
                self.need("-")
            e, types, bounds, inline = self.edge_body()
            forward = self.take("->")
            if not forward:
                self.need("-")
                forward = self.take(">")
            direction = BOTH if back == forward else IN if back else OUT
            w, w_labels, w_conditions = self.node_pattern()
            walked += 1
            if path and bounds:
                e, path = path, None
            if e in seen | {w}:
                raise PlanError(f"{e} is both vertex and edge")
            conditions += inline + w_conditions
            target = w if w not in seen else self.fresh()
            if bounds:
                low, up = bounds
                if self.mode == "walk" and up is None:
                    raise PlanError("walks need an upper bound")
                plan = WalkVar(plan, v, e, types, target, w_labels, direction, low, up, self.mode)
            else:
                plan = Walk(plan, v, e, types, target, w_labels, direction)
            if target != w:
                plan = Select(plan, Op("=", (Var(target), Var(w))))
            seen |= {w, target}
            v = w
        if path:
            raise PlanError("a named path needs a variable-length edge")
        return Select(plan, all_of(conditions)) if conditions else plan

    def edge_body(self):
        e, types, bounds, inline = self.fresh(), [], None, []
        if self.take("["):
            if self.tokens[self.at][0] == "name":
                e = self.name()
            if self.take(":"):
                types.append(self.name())
                while self.take("|"):
                    self.take(":")
                    types.append(self.name())
            if self.take("*"):
                low = self.number() if self.tokens[self.at][0] == "num" else None
                if self.take(".."):
                    up = self.number() if self.tokens[self.at][0] == "num" else None
                    bounds = (1 if low is None else low, up)
                else:
                    bounds = (1, None) if low is None else (low, low)
                if bounds[1] is not None and bounds[1] < bounds[0]:
                    raise PlanError("upper bound below lower bound")
            inline = self.inline(e)
            if inline and bounds:
                raise PlanError("properties of variable-length edges are not compared inline")
            self.need("]")
        return e, tuple(types), bounds, inline

    # -- conditions
    def known(self, e: Any) -> Any:
        self.check(e, kinds(self.plan) if self.plan is not None else {})
        return e

    @staticmethod
    def check(e: Any, scope: dict[str, str]) -> None:
        for v in variables(e):
            if v not in scope:
                raise PlanError(f"{v} is not bound")

    def filtered(self, plan: Node, cond: Any) -> Node:
        if has_agg(cond):
            raise PlanError("aggregates stand in WITH and RETURN only")
        plain = []
        for c in conjuncts(cond):
            negated = isinstance(c, Op) and c.name == "not" and isinstance(c.args[0], Pattern)
            if isinstance(c, Pattern) or negated:
                inner = (c.args[0] if negated else c).plan
                plan = (Anti if negated else Semi)(plan, inner)
            elif any(isinstance(x, Pattern) for x in parts(c)):
                plan, c = self.marked(plan, c)
                self.check(c, kinds(plan))
                plain.append(c)
            else:
                self.check(c, kinds(plan))
                plain.append(c)
        return Select(plan, all_of(plain)) if plain else plan

    def marked(self, plan: Node, cond: Any) -> tuple[Node, Any]:
        """A condition with patterns under OR: each becomes a mark on the rows that have a match, and the condition reads the marks."""
        for pattern in dict.fromkeys(x for x in parts(cond) if isinstance(x, Pattern)):
            own = kinds(pattern.plan)
            shared = [n for n in kinds(plan) if n in own]
            if not shared:
                raise PlanError("a pattern under OR starts from a bound variable")
            mark = self.fresh()
            there = Distinct(Project(pattern.plan, tuple((n, Var(n)) for n in shared)))
            plan = LeftOuter(plan, Project(there, (*((n, Var(n)) for n in shared), (mark, Lit(True)))))
            cond = replaced(cond, lambda x, p=pattern, m=mark: Op("is not null", (Var(m),)) if x == p else None)
        return plan, cond

    # -- results
    def result(self) -> None:
        plan = self.plan or Dual()
        distinct = self.take("distinct")
        scope, items = kinds(plan), []
        while True:
            if self.take("*"):
                items += [(n, Var(n)) for n in scope if not n.startswith("_")]
            else:
                start = self.at
                e = self.expression()
                self.check(e, scope)
                text = "".join(v for _, v in self.tokens[start : self.at])
                items.append((self.name() if self.take("as") else e.name if isinstance(e, Var) else text, e))
            if not self.take(","):
                break
        order, skip, limit = [], 0, None
        if self.take("order"):
            self.need("by")
            while True:
                e = self.expression()
                order.append((e, not self.take("desc", "descending")))
                self.take("asc", "ascending")
                if not self.take(","):
                    break
        if self.take("skip"):
            skip = self.number()
        if self.take("limit"):
            limit = self.number()
        grouped = any(has_agg(e) for _, e in items)
        hidden = []
        for i, (e, up) in enumerate(order):
            same = next((n for n, x in items if x == e), None)
            whole = {n for n, x in items if x == Var(n)}
            over_result = variables(e) <= {n for n, _ in items} and {v for v, _ in properties(e)} <= whole
            if same is None and not over_result:
                if grouped or distinct:
                    raise PlanError("ORDER BY a result column here")
                self.check(e, scope)
                same = f"_order{i}"
                hidden.append((same, e))
            order[i] = (Var(same) if same else e, up)
        plan = self.grouped(plan, items) if grouped else Project(plan, tuple([*items, *hidden]))
        if distinct:
            plan = Distinct(plan)
        if order or skip or limit is not None:
            plan = SortTop(plan, tuple(order), skip, limit)
        if hidden:
            plan = Project(plan, tuple((n, Var(n)) for n, _ in items))
        self.plan = plan

    def grouped(self, plan: Node, items: list[tuple[str, Any]]) -> Node:
        """Items without aggregates are the keys; expressions over aggregates follow in a projection."""
        keys = tuple((n, e) for n, e in items if not has_agg(e))
        outs, after = [], []
        for n, e in items:
            if isinstance(e, Agg):
                outs.append((n, e))
                after.append((n, Var(n)))
            elif has_agg(e):
                def swap(x):
                    if isinstance(x, Agg):
                        outs.append((self.fresh(), x))
                        return Var(outs[-1][0])
                    return None

                after.append((n, replaced(e, swap)))
            else:
                after.append((n, Var(n)))
        made = Group(plan, keys, tuple(outs))
        return made if all(e == Var(n) for n, e in after) and [n for n, _ in after] == [n for n, _ in (*keys, *outs)] else Project(made, tuple(after))

    # -- expressions
    def expression(self) -> Any:
        return self._chain(("or",), lambda: self._chain(("xor",), lambda: self._chain(("and",), self._not)))

    def _chain(self, words, inner):
        found = [inner()]
        while self.peek(*words):
            self.at += 1
            found.append(inner())
        if words == ("xor",):
            out = found[0]
            for x in found[1:]:
                out = Op("xor", (out, x))
            return out
        return found[0] if len(found) == 1 else Op(words[0], tuple(found))

    def _not(self):
        return Op("not", (self._not(),)) if self.take("not") else self._compare()

    def _compare(self):
        left = self._sum()
        if self.take("is"):
            negated = self.take("not")
            self.need("null")
            return Op("is not null" if negated else "is null", (left,))
        if self.take("starts", "ends"):
            word = self.tokens[self.at - 1][1].lower()
            self.need("with")
            return Op(f"{word} with", (left, self._sum()))
        if self.take("contains"):
            return Op("contains", (left, self._sum()))
        if self.take("in"):
            return Op("in", (left, self._sum()))
        if self.peek("=", "<>", "<", "<=", ">", ">="):
            sign = self.tokens[self.at][1]
            self.at += 1
            return Op(sign, (left, self._sum()))
        return left

    def _sum(self):
        out = self._product()
        while self.peek("+", "-"):
            sign = self.tokens[self.at][1]
            self.at += 1
            out = Op(sign, (out, self._product()))
        return out

    def _product(self):
        out = self._unary()
        while self.peek("*", "/", "%"):
            sign = self.tokens[self.at][1]
            self.at += 1
            out = Op(sign, (out, self._unary()))
        return out

    def _unary(self):
        return Op("neg", (self._unary(),)) if self.take("-") else self._postfix()

    def _postfix(self):
        out = self._atom()
        while True:
            if isinstance(out, Var) and self.peek(".") and not self.peek(".."):
                self.at += 1
                value = self.plan is not None and kinds(self.plan).get(out.name) == "value"
                out = Call("field", (out, Lit(self.name()))) if value else Prop(out.name, self.name())
            elif self.take("["):
                out = Op("index", (out, self.expression()))
                self.need("]")
            elif isinstance(out, Var) and self.peek(":"):
                labels = []
                while self.take(":"):
                    labels.append(self.name())
                out = HasLabels(out.name, tuple(labels))
            else:
                return out

    def _is_pattern(self) -> bool:
        depth, at = 0, self.at
        while at < len(self.tokens):
            value = self.tokens[at][1]
            depth += (value == "(") - (value == ")")
            at += 1
            if depth == 0:
                following = [t[1] for t in self.tokens[at : at + 2]]
                return following[:1] == ["<-"] or following in (["-", "["], ["<", "-"]) or (following == ["-", "("]) or following[:1] == ["->"]
        return False

    def _atom(self):
        kind, value = self.tokens[self.at]
        word = value.lower()
        if kind == "num":
            self.at += 1
            return Lit(float(value) if "." in value else int(value))
        if kind == "str":
            self.at += 1
            return Lit(re.sub(r"\\(.)", r"\1", value[1:-1]))
        if value == "(":
            if self._is_pattern():
                return Pattern(self.pattern())
            self.at += 1
            e = self.expression()
            self.need(")")
            return e
        if self.take("["):
            items = []
            while not self.take("]"):
                items.append(self.expression())
                self.take(",")
            return Lit(tuple(x.value for x in items)) if items and all(isinstance(x, Lit) for x in items) else Call("list", tuple(items))
        if kind == "name" and self.tokens[self.at + 1][1] == "(" and word not in _CLAUSES:
            return self._call()
        if word in ("true", "false", "null"):
            self.at += 1
            return Lit({"true": True, "false": False, "null": None}[word])
        return Var(self.name())

    def _call(self):
        word = self.name().lower()
        self.need("(")
        if word in ("all", "any", "none", "filter", "transform") and self.peek("in", ahead=1):
            name = self.name()
            self.need("in")
            items = self.expression()
            self.need("where", "|")
            body = self.expression()
            self.need(")")
            return Each(word, name, items, body)
        if word == "exists" and self.peek("("):
            inner = Pattern(self.pattern())
            self.need(")")
            return inner
        distinct = self.take("distinct")
        if word == "count" and self.take("*"):
            self.need(")")
            return Agg("count", None)
        args = []
        while not self.take(")"):
            args.append(self.expression())
            self.take(",")
        if word in _AGGREGATES:
            if any(has_agg(a) for a in args):
                raise PlanError("an aggregate inside an aggregate: use WITH")
            return Agg(word, args[0], distinct, args[1].value if len(args) > 1 else None)
        if distinct:
            raise PlanError(f"{word} takes no DISTINCT")
        if word in ("labels", "type", "id") and isinstance(args[0], Var):
            return {"labels": Prop(args[0].name, LABELS), "type": Prop(args[0].name, TYPE), "id": args[0]}[word]
        if word in ("startnode", "endnode") and isinstance(args[0], Var):
            return Prop(args[0].name, "@src" if word == "startnode" else "@trg")
        return Call(word, tuple(args))


def parse(text: str, mode: str = "trail") -> Node:
    """The graph plan of a query."""
    return Parser(text, mode).query()
