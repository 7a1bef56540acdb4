"""A text query language over triples.

A subset of the usual graph query language: select (distinct, count and other
aggregates), ask, construct; basic patterns with ``;`` and ``,``, filter, optional,
union; path operators ``/ ^ | + *``; group by, having, order by, limit, offset.
Text becomes a small tree, and the tree DataFrames: a pattern is a filtered scan
of the predicate-partitioned triples, shared variables are the join keys.
"""

from __future__ import annotations

import re
from dataclasses import dataclass, field

from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

TOKEN = re.compile(r"""\s*(?:(?P<str>"(?:[^"\\]|\\.)*")|(?P<var>\?\w+)|(?P<num>-?\d+(?:\.\d+)?)|(?P<name>[A-Za-z_][\w-]*:(?:[\w%#=-]|\.(?=\w)|/(?![A-Za-z_][\w-]*:|[\^(]))+|[A-Za-z_]\w*)|(?P<op>&&|\|\||!=|<=|>=|[{}().;,=<>!*+/^|-]))""")
AGGREGATES = ("count", "sum", "avg", "min", "max")
MAX_DEPTH = 32


class QueryError(ValueError):
    pass


@dataclass
class Query:
    form: str = "select"
    distinct: bool = False
    items: list = field(default_factory=list)
    """(expression, name) of the result's columns; empty: all variables."""
    template: list = field(default_factory=list)
    where: list = field(default_factory=list)
    group: list[str] = field(default_factory=list)
    having: list = field(default_factory=list)
    order: list = field(default_factory=list)
    limit: int | None = None
    offset: int = 0


def tokens(text: str) -> list[tuple[str, str]]:
    out, at, text = [], 0, text.strip()
    while at < len(text):
        m = TOKEN.match(text, at)
        if not m or m.end() == at:
            raise QueryError(f"can't read {text[at : at + 20]!r}")
        kind = m.lastgroup
        out.append((kind, m[kind]))
        at = m.end()
        while at < len(text) and text[at].isspace():
            at += 1
    return out


class Parser:
    def __init__(self, text: str):
        self.toks, self.at = tokens(text), 0

    def peek(self) -> str:
        return self.toks[self.at][1] if self.at < len(self.toks) else ""

    def kind(self) -> str:
        return self.toks[self.at][0] if self.at < len(self.toks) else ""

    def next(self) -> str:
        self.at += 1
        return self.toks[self.at - 1][1]

    def word(self, *options: str) -> bool:
        if self.peek().lower() in options:
            self.at += 1
            return True
        return False

    def need(self, s: str) -> None:
        if not self.word(s):
            raise QueryError(f"{s} expected before {self.peek()!r}")

    def query(self) -> Query:
        q = Query()
        if self.word("ask"):
            q.form = "ask"
        elif self.word("construct"):
            q.form = "construct"
            self.need("{")
            q.template = self.triples_block()
        else:
            self.need("select")
            q.distinct = self.word("distinct")
            while self.peek().lower() not in ("where", "{"):
                if self.word("*"):
                    continue
                if self.kind() == "var":
                    v = self.next()[1:]
                    q.items.append((("var", v), v))
                else:
                    self.need("(")
                    e = self.expression()
                    self.need("as")
                    q.items.append((e, self.next()[1:]))
                    self.need(")")
        self.word("where")
        self.need("{")
        q.where = self.group()
        while self.at < len(self.toks):
            if self.word("group"):
                self.need("by")
                while self.kind() == "var":
                    q.group.append(self.next()[1:])
            elif self.word("having"):
                q.having.append(self.expression())
            elif self.word("order"):
                self.need("by")
                while self.kind() == "var" or self.peek().lower() in ("asc", "desc"):
                    way = "desc" if self.peek().lower() == "desc" else "asc"
                    if self.kind() != "var":
                        self.next()
                        self.need("(")
                        q.order.append((self.next()[1:], way))
                        self.need(")")
                    else:
                        q.order.append((self.next()[1:], way))
            elif self.word("limit"):
                q.limit = int(self.next())
            elif self.word("offset"):
                q.offset = int(self.next())
            else:
                raise QueryError(f"unexpected {self.peek()!r}")
        return q

    def group(self) -> list:
        """Elements up to the closing brace."""
        out: list = []
        while not self.word("}"):
            if self.at >= len(self.toks):
                raise QueryError("a brace isn't closed")
            if self.word("filter"):
                out.append(("filter", self.expression()))
            elif self.word("optional"):
                self.need("{")
                out.append(("optional", self.group()))
            elif self.word("{"):
                parts = [self.group()]
                while self.word("union"):
                    self.need("{")
                    parts.append(self.group())
                out.append(("union", parts))
            elif not self.word("."):
                out += [("triple", t) for t in self.subject()]
        return out

    def triples_block(self) -> list:
        out: list = []
        while not self.word("}"):
            if not self.word("."):
                out += self.subject()
        return out

    def subject(self) -> list:
        s, out = self.term(), []
        while True:
            p = self.path()
            while True:
                out.append((s, p, self.term()))
                if not self.word(","):
                    break
            if not self.word(";"):
                return out

    def path(self) -> tuple:
        left = self.sequence()
        while self.word("|"):
            left = ("or", left, self.sequence())
        return left

    def sequence(self) -> tuple:
        left = self.step()
        while self.word("/"):
            left = ("then", left, self.step())
        return left

    def step(self) -> tuple:
        if self.word("^"):
            return ("inverse", self.step())
        if self.word("("):
            p = self.path()
            self.need(")")
        elif self.kind() == "var":
            p = ("any", self.next()[1:])
        else:
            name = self.next()
            p = ("pred", "rdf:type" if name == "a" else name)
        if self.word("+"):
            return ("plus", p)
        return ("star", p) if self.word("*") else p

    def term(self) -> tuple:
        kind, text = self.kind(), self.next()
        if kind == "var":
            return ("var", text[1:])
        if kind == "str":
            return ("const", re.sub(r"\\(.)", r"\1", text[1:-1]))
        return ("const", text)

    def expression(self) -> tuple:
        left = self.both()
        while self.word("||"):
            left = ("or", left, self.both())
        return left

    def both(self) -> tuple:
        left = self.compare()
        while self.word("&&"):
            left = ("and", left, self.compare())
        return left

    def compare(self) -> tuple:
        left = self.atom()
        if self.peek() in ("=", "!=", "<", ">", "<=", ">="):
            op = self.next()
            return ("cmp", op, left, self.atom())
        return left

    def atom(self) -> tuple:
        if self.word("!"):
            return ("not", self.atom())
        if self.word("("):
            e = self.expression()
            self.need(")")
            return e
        kind, low = self.kind(), self.peek().lower()
        if low in AGGREGATES or low in ("bound", "regex"):
            self.next()
            self.need("(")
            distinct, args = self.word("distinct"), []
            while not self.word(")"):
                if self.word("*"):
                    args.append(("all",))
                elif not self.word(","):
                    args.append(self.expression())
            return ("call", low, distinct, args)
        if kind == "num":
            return ("num", float(self.next()))
        return self.term()


def _value(e: tuple, numeric: bool = False) -> Column:
    if e[0] == "var":
        return F.expr(f"try_cast(`{e[1]}` as double)") if numeric else F.col(e[1])
    return F.lit(e[1])


def _condition(e: tuple) -> Column:
    if e[0] in ("and", "or"):
        a, b = _condition(e[1]), _condition(e[2])
        return a & b if e[0] == "and" else a | b
    if e[0] == "not":
        return ~_condition(e[1])
    if e[0] == "call" and e[1] == "bound":
        return F.col(e[3][0][1]).isNotNull()
    if e[0] == "call" and e[1] == "regex":
        return F.rlike(_value(e[3][0]), F.lit(e[3][1][1]))
    if e[0] != "cmp":
        raise QueryError(f"not a condition: {e[0]}")
    numeric = "num" in (e[2][0], e[3][0])
    a, b = _value(e[2], numeric), _value(e[3], numeric)
    return {"=": a == b, "!=": a != b, "<": a < b, ">": a > b, "<=": a <= b, ">=": a >= b}[e[1]]


def _aggregate(e: tuple) -> Column:
    if e[0] != "call" or e[1] not in AGGREGATES:
        raise QueryError("an aggregate is expected")
    _, name, distinct, args = e
    if name == "count":
        if args[0] == ("all",):
            return F.count("*")
        return F.countDistinct(F.col(args[0][1])) if distinct else F.count(F.col(args[0][1]))
    x = _value(args[0], True)
    return {"sum": F.sum, "avg": F.avg, "min": F.min, "max": F.max}[name](x)


class Executor:
    """Runs queries over triples (s, p, o)."""

    def __init__(self, triples: DataFrame):
        self.t = triples.select("s", "p", "o")

    def query(self, text: str) -> DataFrame:
        return self.run(Parser(text).query())

    def run(self, q: Query) -> DataFrame:
        df = self.group(q.where)
        if q.form == "ask":
            return df.agg((F.count("*") > 0).alias("answer"))
        if q.form == "construct":
            one = [F.struct(*(_value(x).cast("string").alias(n) for x, n in zip((s, p if p[0] == "any" and ("var", p[1]) else p, o), "spo", strict=True))) for s, p, o in ((s, ("var", p[1]) if p[0] == "any" else ("const", p[1]), o) for s, p, o in q.template)]
            return df.select(F.inline(F.array(*one))).where("s is not null and p is not null and o is not null").distinct()
        grouped = [(e, n) for e, n in q.items if e[0] == "call"]
        if q.group or grouped:
            aggs = [_aggregate(e).alias(n) for e, n in grouped]
            extra = []
            for k, h in enumerate(q.having):
                if h[0] == "cmp" and h[2][0] == "call":
                    aggs.append(_aggregate(h[2]).alias(f"__h{k}"))
                    extra.append(("cmp", h[1], ("var", f"__h{k}"), h[3]))
                else:
                    extra.append(h)
            df = df.groupBy(*q.group).agg(*aggs)
            for h in extra:
                df = df.where(_condition(h))
        if q.order:
            df = df.orderBy(*(F.col(v).asc() if way == "asc" else F.col(v).desc() for v, way in q.order))
        if q.items:
            df = df.select(*(F.col(n) if e[0] in ("var", "call") else _value(e).alias(n) for e, n in q.items))
        if q.distinct:
            df = df.distinct()
        if q.offset:
            df = df.offset(q.offset)
        return df.limit(q.limit) if q.limit is not None else df

    def group(self, parts: list) -> DataFrame:
        df, filters = None, []
        for kind, x in parts:
            if kind == "filter":
                filters.append(x)
            elif kind == "optional":
                df = self.join(df, self.group(x), "left")
            elif kind == "union":
                both = [self.group(p) for p in x]
                one = both[0]
                for other in both[1:]:
                    one = one.unionByName(other, allowMissingColumns=True)
                df = one if df is None else self.join(df, one)
            else:
                one = self.pattern(*x)
                df = one if df is None else self.join(df, one)
        if df is None:
            raise QueryError("an empty group")
        for f in filters:
            df = df.where(_condition(f))
        return df

    def join(self, a: DataFrame | None, b: DataFrame, how: str = "inner") -> DataFrame:
        if a is None:
            return b
        shared = [c for c in b.columns if c in a.columns]
        if not shared:
            raise QueryError("patterns without a shared variable would be a cross join")
        return a.join(b, shared, how)

    def pattern(self, s: tuple, p: tuple, o: tuple) -> DataFrame:
        e = self.edges(p)
        names, used = [], {}
        for col, term in (("s", s), ("o", o)):
            if term[0] == "var":
                if term[1] in used:
                    e = e.where(F.col(col) == F.col(used[term[1]]))
                else:
                    used[term[1]] = col
                    names.append(F.col(col).alias(term[1]))
            else:
                e = e.where(F.col(col) == F.lit(term[1]))
        if p[0] == "any":
            names.append(F.col("p").alias(p[1]))
        return e.select(*names) if names else e.select(F.lit(True).alias("__hit")).limit(1)

    def edges(self, p: tuple) -> DataFrame:
        """(s, o) of a path; with p for a variable predicate."""
        if p[0] == "pred":
            return self.t.where(F.col("p") == p[1]).select("s", "o")
        if p[0] == "any":
            return self.t
        if p[0] == "inverse":
            return self.edges(p[1]).select(F.col("o").alias("s"), F.col("s").alias("o"))
        if p[0] == "or":
            return self.edges(p[1]).unionByName(self.edges(p[2]))
        if p[0] == "then":
            a = self.edges(p[1]).select("s", F.col("o").alias("m"))
            return a.join(self.edges(p[2]).select(F.col("s").alias("m"), "o"), "m").select("s", "o")
        one = self.edges(p[1]).distinct()
        one.createOrReplaceTempView("__cg_path")
        plus = one.sparkSession.sql(f"""
            WITH RECURSIVE r(s, o, n) AS (SELECT s, o, 1 FROM __cg_path UNION ALL SELECT r.s, e.o, r.n + 1 FROM r JOIN __cg_path e ON e.s = r.o WHERE r.n < {MAX_DEPTH})
            SELECT DISTINCT s, o FROM r""")
        if p[0] == "plus":
            return plus
        nodes = self.t.select(F.explode(F.array("s", "o")).alias("s")).distinct()
        return plus.unionByName(nodes.select("s", F.col("s").alias("o"))).distinct()
