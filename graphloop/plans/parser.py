"""Text front end: procedures and the query language they use, by recursive descent."""

from __future__ import annotations

import re

from graphloop.plans import query as q
from graphloop.plans.procedure import AskTrue, Fixpoint, Let, Loop, Procedure, Return, Times
from graphloop.terms import SHIFT, TAGS

_TOKEN = re.compile(
    r"""\s+|\#[^\n]*|(?P<iri><[^<>\s]*>)|(?P<var>[?$]\w+)|(?P<num>\d+\.\d*|\.\d+|\d+)|(?P<str>"(?:[^"\\]|\\.)*"|'(?:[^'\\]|\\.)*')"""
    r"""|(?P<name>[A-Za-z_]\w*(?::[A-Za-z_][\w]*)?)|(?P<op>&&|\|\||!=|<=|>=|[{}()\[\].;,=<>+\-*/!|^?])""",
    re.X,
)
_AGGREGATES = {"count", "sum", "avg", "min", "max", "sample", "group_concat"}


class SyntaxProblem(ValueError):
    """Text that is not in the language; says where."""


def _tokens(text: str) -> list[tuple[str, str, int]]:
    out, at = [], 0
    while at < len(text):
        m = _TOKEN.match(text, at)
        if not m:
            raise SyntaxProblem(f"unexpected {text[at]!r} at {at}")
        if m.lastgroup:
            out.append((m.lastgroup, m.group(), at))
        at = m.end()
    return [*out, ("end", "", len(text))]


class _Parser:
    def __init__(self, text: str):
        self.tokens, self.at = _tokens(text), 0

    # Token helpers

    def peek(self, *words: str) -> bool:
        kind, text, _ = self.tokens[self.at]
        return kind in ("name", "op") and text.lower() in words

    def take(self, *words: str) -> bool:
        if self.peek(*words):
            self.at += 1
            return True
        return False

    def need(self, word: str) -> None:
        if not self.take(word):
            kind, text, at = self.tokens[self.at]
            raise SyntaxProblem(f"expected {word!r} but found {text or 'the end'!r} at {at}")

    def kind(self, kind: str) -> str | None:
        if self.tokens[self.at][0] == kind:
            self.at += 1
            return self.tokens[self.at - 1][1]
        return None

    def name(self) -> str:
        found = self.kind("name")
        if found is None:
            raise SyntaxProblem(f"expected a name at {self.tokens[self.at][2]}")
        return found

    def var(self) -> str:
        found = self.kind("var")
        if found is None:
            raise SyntaxProblem(f"expected a variable at {self.tokens[self.at][2]}")
        return found[1:]

    # Procedures

    def procedure(self) -> Procedure:
        proc = Procedure(self.statements())
        if self.tokens[self.at][0] != "end":
            raise SyntaxProblem(f"unexpected {self.tokens[self.at][1]!r} at {self.tokens[self.at][2]}")
        return proc

    def statements(self) -> list:
        out = []
        while self.peek("let", "do", "return"):
            if self.take("let"):
                name = self.name()
                self.need("=")
                self.need("(")
                out.append(Let(name, self.select()))
                self.need(")")
            elif self.take("do"):
                self.need("(")
                body = self.statements()
                self.need(")")
                self.need("while")
                self.need("(")
                out.append(Loop(tuple(body), self.condition()))
                self.need(")")
            else:
                self.need("return")
                self.need("(")
                out.append(Return(self.name()))
                self.need(")")
            self.take(";")
        return out

    def condition(self):
        if self.take("times"):
            return Times(int(self.kind("num") or 0))
        if self.take("fixpoint"):
            self.need("(")
            name = self.name()
            self.need(")")
            return Fixpoint(name)
        self.need("ask")
        return AskTrue(self.group())

    # Queries

    def query(self) -> q.Query:
        if self.take("ask"):
            self.take("where")
            return q.Ask(self.group())
        if self.take("construct"):
            self.need("{")
            template = tuple((p.s, p.p, p.o) for p in self.triples())
            self.need("}")
            self.need("where")
            return q.Construct(template, self.group())
        return self.select()

    def select(self) -> q.Query:
        self.need("select")
        distinct = self.take("distinct")
        self.take("reduced")
        items, aggs, everything = [], [], self.take("*")
        while not everything and not self.peek("where", "{"):
            if self.take("("):
                value = self.expression(aggs)
                self.need("as")
                items.append((value, self.var()))
                self.need(")")
            else:
                items.append(self.var())
        self.take("where")
        body = self.group()
        keys, having, order = [], None, []
        if self.take("group"):
            self.need("by")
            while self.peek("(") or self.tokens[self.at][0] == "var":
                if self.take("("):
                    value = self.expression([])
                    self.need("as")
                    keys.append((value, self.var()))
                    self.need(")")
                else:
                    keys.append(self.var())
        if self.take("having"):
            having = self.expression(aggs)
        if aggs or keys:
            body = q.Group(body, tuple(keys), tuple(aggs), having)
        if self.take("order"):
            self.need("by")
            while self.peek("asc", "desc", "(") or self.tokens[self.at][0] == "var":
                down = self.take("desc")
                if not down:
                    self.take("asc")
                order.append((self.primary([]), down))
        if not everything:
            scope = [i if isinstance(i, str) else i[1] for i in items]
            plain = {i for i in items if isinstance(i, str)}
            extra = tuple(v for e, _ in order for v in _vars(e) if v not in scope)
            body = q.Project(body, tuple(items) + tuple(v for v in dict.fromkeys(extra) if v not in plain))
            kept = tuple(scope)
        if distinct:
            body = q.Distinct(body)
        limit = offset = None
        while self.peek("limit", "offset"):
            if self.take("limit"):
                limit = int(self.kind("num"))
            else:
                self.need("offset")
                offset = int(self.kind("num"))
        if order or limit is not None or offset:
            body = q.Slice(body, tuple(order), limit, offset or 0)
        return q.Project(body, kept) if order and not everything else body

    def group(self) -> q.Query:
        self.need("{")
        if self.peek("select"):
            body = self.select()
            self.need("}")
            return body
        body: q.Query | None = None
        filters: list = []

        def joined(part: q.Query) -> q.Query:
            return part if body is None else q.Join(body, part)

        while not self.take("}"):
            if self.take("."):
                continue
            if self.take("optional"):
                inner = self.group()
                condition = None
                if isinstance(inner, q.Filter):  # a filter of the optional part sees both sides
                    inner, condition = inner.body, inner.condition
                body = q.LeftJoin(body or q.Unit(), inner, condition)
            elif self.take("minus"):
                body = q.Minus(body or q.Unit(), self.group())
            elif self.take("filter"):
                negated = self.take("not")
                if negated or self.peek("exists"):
                    self.need("exists")
                    filters.append((self.group(), negated))
                else:
                    filters.append(self.primary([]))
            elif self.take("bind"):
                self.need("(")
                value = self.expression([])
                self.need("as")
                body = q.Extend(body or q.Unit(), self.var(), value)
                self.need(")")
            elif self.take("values"):
                body = joined(self.values())
            elif self.take("qvalues"):
                self.need("(")
                body = joined(q.VarRef(self.name()))
                self.need(")")
            elif self.take("graph"):
                name = self.name()
                body = joined(q.GraphClause(name, self.group()))
            elif self.peek("{"):
                part = self.group()
                while self.take("union"):
                    part = q.Union(part, self.group())
                body = joined(part)
            else:
                body = joined(q.Bgp(tuple(self.triples())))
        body = body or q.Unit()
        for f in filters:
            body = q.Exists(body, f[0], f[1]) if isinstance(f, tuple) else q.Filter(body, f)
        return body

    def triples(self) -> list[q.Pattern]:
        out = []
        while True:
            s = self.term()
            while True:
                p = self.path()
                while True:
                    out.append(q.Pattern(s, p, self.term()))
                    if not self.take(","):
                        break
                if not self.take(";"):
                    break
            if not self.take(".") or self.tokens[self.at][0] not in ("var", "iri", "num", "str"):
                return out

    def values(self) -> q.Values:
        single = self.tokens[self.at][0] == "var"
        names = [self.var()] if single else []
        if not single:
            self.need("(")
            while not self.take(")"):
                names.append(self.var())
        self.need("{")
        rows = []
        while not self.take("}"):
            if single:
                rows.append((self.constant(),))
            else:
                self.need("(")
                rows.append(tuple(self.constant() for _ in names))
                self.need(")")
        return q.Values(tuple(names), tuple(rows))

    def constant(self):
        if self.take("undef"):
            return None
        t = self.term()
        return t.value

    def term(self) -> q.Term:
        kind, text, at = self.tokens[self.at]
        self.at += 1
        if kind == "var":
            return q.Var(text[1:])
        if kind == "num":
            return q.Const(float(text) if "." in text else int(text))
        if kind == "str":
            return q.Const(re.sub(r"\\(.)", r"\1", text[1:-1]))
        if kind == "iri":
            cls, _, key = text[1:-1].partition("/")
            if cls in TAGS and key.isdigit():
                return q.Const((TAGS[cls] << SHIFT) + int(key))
            return q.Const(text[1:-1])
        if kind == "name" and text.lower() in ("true", "false"):
            return q.Const(text.lower() == "true")
        if kind == "op" and text == "-":
            return q.Const(-self.term().value)
        raise SyntaxProblem(f"expected a term but found {text or 'the end'!r} at {at}")

    # Paths: alternatives of sequences of steps

    def path(self):
        if self.tokens[self.at][0] == "var":
            return q.Var(self.var())
        parts = [self.path_sequence()]
        while self.take("|"):
            parts.append(self.path_sequence())
        return parts[0] if len(parts) == 1 else q.Alt(tuple(parts))

    def path_sequence(self):
        parts = [self.path_step()]
        while self.take("/"):
            parts.append(self.path_step())
        return parts[0] if len(parts) == 1 else q.Seq(tuple(parts))

    def path_step(self):
        if self.take("!"):
            names = []
            if self.take("("):
                while not self.take(")"):
                    names.append(self.predicate())
                    self.take("|")
            else:
                names.append(self.predicate())
            return q.Negated(tuple(names))
        if self.take("^"):
            return q.Step(self.predicate(), inverse=True)
        if self.take("("):
            inner = self.path()
            self.need(")")
        else:
            inner = self.predicate()
        if self.take("+"):
            return q.Repeat(inner, 1)
        if self.take("*"):
            return q.Repeat(inner, 0)
        if self.take("?"):
            return q.Repeat(inner, 0, 1)
        return inner

    def predicate(self) -> str:
        return self.name().rpartition(":")[2]

    # Expressions

    _LEVELS = [("||",), ("&&",), ("=", "!=", "<", "<=", ">", ">="), ("+", "-"), ("*", "/")]

    def expression(self, aggs: list, level: int = 0):
        if level == len(self._LEVELS):
            return self.unary(aggs)
        left = self.expression(aggs, level + 1)
        while True:
            if level == 2 and (self.peek("in") or self.peek("not")):
                negated = self.take("not")
                self.need("in")
                self.need("(")
                items = [self.expression(aggs)]
                while self.take(","):
                    items.append(self.expression(aggs))
                self.need(")")
                left = q.call("in", left, *items)
                left = q.call("!", left) if negated else left
                continue
            op = next((o for o in self._LEVELS[level] if self.peek(o)), None)
            if op is None:
                return left
            self.take(op)
            left = q.call(op, left, self.expression(aggs, level + 1))

    def unary(self, aggs: list):
        if self.take("!"):
            return q.call("!", self.unary(aggs))
        if self.take("-"):
            return q.call("neg", self.unary(aggs))
        return self.primary(aggs)

    def primary(self, aggs: list):
        if self.take("("):
            inner = self.expression(aggs)
            self.need(")")
            return inner
        kind, text, _ = self.tokens[self.at]
        if kind == "name" and text.lower() not in ("true", "false"):
            self.at += 1
            fn = text.lower()
            self.need("(")
            if fn in _AGGREGATES:
                distinct = self.take("distinct")
                arg = None if self.take("*") else self.expression([])
                self.need(")")
                hidden = f"_agg{len(aggs)}"
                aggs.append((hidden, q.Agg(fn, arg, distinct)))
                return q.Var(hidden)
            args = []
            while not self.take(")"):
                args.append(self.expression(aggs))
                self.take(",")
            return q.call(fn, *args)
        return self.term()


def _vars(e) -> list[str]:
    if isinstance(e, q.Var):
        return [e.name]
    return [v for a in e.args for v in _vars(a)] if isinstance(e, q.Call) else []


def parse_procedure(text: str) -> Procedure:
    """A procedure from text. Keywords are case-insensitive, # starts a comment, prefixes of names are dropped."""
    return _Parser(text).procedure()


def parse_query(text: str) -> q.Query:
    """A SELECT, ASK or CONSTRUCT query from text."""
    parser = _Parser(text)
    found = parser.query()
    if parser.tokens[parser.at][0] != "end":
        raise SyntaxProblem(f"unexpected {parser.tokens[parser.at][1]!r} at {parser.tokens[parser.at][2]}")
    return found
