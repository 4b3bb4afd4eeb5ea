"""Source text to trees, as flat pre-order rows that carry what pair counting needs.

Languages: a JavaScript subset (statements, functions, calls, members, chains, literals,
operators), Python by its own ``ast``, and HTML. A row holds the enclosing calls (outermost
first) and the next sibling if that is a call, so pairs need no join. A statement that is only
an expression is that expression; other nodes are transparent for nesting, not for
neighbourhood. Walks keep their own stack, so depth is bounded by memory only; sources that do
not parse give no rows and an error, and stay in the table of the check.
"""

from __future__ import annotations

import ast
import re
from collections.abc import Iterator
from html.parser import HTMLParser

import pyarrow as pa
from pyspark.sql import Column, DataFrame
from pyspark.sql import functions as F

NODE_FIELDS = ("node_id", "parent_id", "pos", "depth", "kind", "op", "call_path", "next_call")
NODE_DDL = "script_id string, node_id int, parent_id int, pos int, depth int, kind string, op string, call_path array<string>, next_call string"


class Node:
    """A tree node; ``op`` is a call's operator or an element's tag."""

    __slots__ = ("kind", "op", "children")

    def __init__(self, kind: str, op: str | None = None, children: list[Node] | None = None) -> None:
        self.kind, self.op, self.children = kind, op, children if children is not None else []

    @property
    def calls(self) -> bool:
        return self.kind in ("call", "element")


# --- JavaScript ---------------------------------------------------------------------------

_JS = re.compile(
    r"(?P<skip>\s+|//[^\n]*|/\*.*?\*/)|(?P<str>'(?:\\.|[^'\\\n])*'|\"(?:\\.|[^\"\\\n])*\"|`(?:\\.|[^`\\])*`)"
    r"|(?P<num>0[xXbBoO][\da-fA-F]+|\d+\.?\d*(?:[eE][+-]?\d+)?|\.\d+(?:[eE][+-]?\d+)?)|(?P<name>[A-Za-z_$\u0080-￿][\w$\u0080-￿]*)"
    r"|(?P<op>=>|\.\.\.|\?\.(?!\d)|\?\?=?|[=!]==?|>>>=?|<<=?|>>=?|&&=?|\|\|=?|\*\*=?|\+\+|--|[-+*/%&|^<>]=?|[(){}\[\];,?:.=!~@#])",
    re.S,
)
_WORDS = frozenset("if else for while do switch case default break continue return throw try catch finally function class var let const new typeof void delete in of instanceof import export async await yield extends static".split())
_BINDING = {
    "=": 1, "+=": 1, "-=": 1, "*=": 1, "/=": 1, "%=": 1, "**=": 1, "&=": 1, "|=": 1, "^=": 1, "<<=": 1, ">>=": 1, ">>>=": 1, "&&=": 1, "||=": 1, "??=": 1,
    "=>": 1, "?": 2, "??": 3, "||": 3, "&&": 4, "|": 5, "^": 6, "&": 7, "==": 8, "!=": 8, "===": 8, "!==": 8, "<": 9, ">": 9, "<=": 9, ">=": 9, "in": 9, "of": 9,
    "instanceof": 9, "<<": 10, ">>": 10, ">>>": 10, "+": 11, "-": 11, "*": 12, "/": 12, "%": 12, "**": 13,
}


def js_tokens(source: str) -> list[tuple[str, str, bool]]:
    """Kind, text and whether a line break stands before; comments are left out."""
    out, at, line = [], 0, False
    while at < len(source):
        m = _JS.match(source, at)
        if m is None:
            raise SyntaxError(f"unexpected {source[at]!r} at {at}")
        at = m.end()
        if m.lastgroup == "skip":
            line |= "\n" in m[0]
            continue
        kind = "word" if m.lastgroup == "name" and m[0] in _WORDS else m.lastgroup
        out.append((kind, m[0], line))
        line = False
    return out


class JsParser:
    def __init__(self, source: str, roots: frozenset[str]) -> None:
        self.t, self.i, self.roots = js_tokens(source), 0, roots

    def peek(self) -> str:
        return self.t[self.i][1] if self.i < len(self.t) and self.t[self.i][0] != "str" else ""

    def take(self, text: str | None = None) -> str:
        if self.i >= len(self.t) or (text is not None and self.peek() != text):
            raise SyntaxError(f"expected {text} at token {self.i}")
        self.i += 1
        return self.t[self.i - 1][1]

    def maybe(self, text: str) -> bool:
        if self.peek() == text:
            self.i += 1
            return True
        return False

    def program(self) -> Node:
        top = Node("program")
        while self.i < len(self.t):
            top.children += self.statement()
        return top

    def block(self) -> Node:
        self.take("{")
        out = Node("block")
        while not self.maybe("}"):
            out.children += self.statement()
        return out

    def statement(self) -> list[Node]:
        word = self.peek() if self.i < len(self.t) and self.t[self.i][0] == "word" else ""
        if self.maybe(";"):
            return []
        if self.peek() == "{":
            return [self.block()]
        if word in ("var", "let", "const"):
            self.take()
            found = Node("declaration", children=self.listed(None))
            self.maybe(";")
            return [found]
        if word in ("if", "while", "switch"):
            self.take()
            self.take("(")
            head = Node(word, children=self.listed(")"))
            head.children += self.cases() if word == "switch" else self.statement()
            if word == "if" and self.maybe("else"):
                head.children += self.statement()
            return [head]
        if word == "for":
            self.take()
            self.maybe("await")
            self.take("(")
            head = Node("for")
            while not self.maybe(")"):
                if self.peek() in ("var", "let", "const", ";", ","):
                    self.take()
                else:
                    head.children.append(self.expression(0))
            head.children += self.statement()
            return [head]
        if word == "do":
            self.take()
            head = Node("do", children=self.statement())
            self.take("while")
            self.take("(")
            head.children += self.listed(")")
            self.maybe(";")
            return [head]
        if word == "try":
            self.take()
            head = Node("try", children=[self.block()])
            if self.maybe("catch"):
                if self.maybe("("):
                    self.listed(")")
                head.children.append(self.block())
            if self.maybe("finally"):
                head.children.append(self.block())
            return [head]
        if word in ("return", "throw"):
            self.take()
            head = Node(word)
            if self.i < len(self.t) and self.peek() not in (";", "}") and not self.t[self.i][2]:
                head.children = self.listed(None)
            self.maybe(";")
            return [head]
        if word in ("break", "continue", "import", "export"):
            self.take()
            while self.i < len(self.t) and self.peek() not in (";", "}") and not self.t[self.i][2] and word in ("break", "continue", "import"):
                self.take()
            self.maybe("default")
            self.maybe(";")
            return []
        found = self.listed(None)
        self.maybe(";")
        return found

    def cases(self) -> list[Node]:
        self.take("{")
        out: list[Node] = []
        while not self.maybe("}"):
            if self.maybe("case"):
                out.append(self.expression(0))
                self.take(":")
            elif self.maybe("default"):
                self.take(":")
            else:
                out += self.statement()
        return out

    def listed(self, end: str | None) -> list[Node]:
        """Expressions with commas between them, up to and with ``end``."""
        out: list[Node] = []
        while end is None or not self.maybe(end):
            if self.maybe(","):
                continue
            out.append(self.expression(0))
            if end is None and not self.maybe(","):
                break
            if end is not None and self.peek() not in (",", end):
                raise SyntaxError(f"expected {end} at token {self.i}")
        return out

    def expression(self, least: int) -> Node:
        left = self.postfix(self.primary())
        while (power := _BINDING.get(self.peek(), 0)) > least or (power == 1 and least <= 1 and power > 0):
            sign = self.take()
            if sign == "=>":
                body = self.block() if self.peek() == "{" else self.expression(1)
                left = Node("function", children=[body])
            elif sign == "?":
                yes = self.expression(1)
                self.take(":")
                left = Node("choice", children=[left, yes, self.expression(1)])
            else:
                right = self.expression(power - 1 if sign in ("**",) or power == 1 else power)
                left = Node("assign" if power == 1 else "operator", sign, [left, right])
        return left

    def primary(self) -> Node:
        if self.i >= len(self.t):
            raise SyntaxError("the source ends early")
        kind, text, _ = self.t[self.i]
        self.i += 1
        if kind in ("str", "num"):
            return Node("literal")
        if kind == "name":
            return Node("name", text)
        if text == "(":
            inside = self.listed(")")
            return inside[0] if len(inside) == 1 and self.peek() != "=>" else Node("group", children=inside)
        if text == "[":
            return Node("array", children=self.listed("]"))
        if text == "{":
            return self.object()
        if text in ("function", "class", "async"):
            return self.function(text)
        if text == "new":
            made = self.postfix(self.primary(), calls=False)
            args = self.listed(")") if self.maybe("(") else []
            return self.call(made, args)
        if text in ("+", "-", "!", "~", "++", "--", "...", "typeof", "void", "delete", "await", "yield"):
            return Node("operator", text, [self.expression(13)])
        if text == "/":  # a pattern: up to the next slash
            while self.take() != "/":
                pass
            if self.i < len(self.t) and self.t[self.i][0] == "name" and not self.t[self.i][2]:
                self.take()
            return Node("literal")
        raise SyntaxError(f"unexpected {text!r} at token {self.i}")

    def function(self, word: str) -> Node:
        if word == "async":
            return self.function("function") if self.maybe("function") else self.primary()
        self.maybe("*")
        if word == "class":
            while self.peek() != "{":
                self.take()
            self.take("{")
            body = Node("class")
            while not self.maybe("}"):
                if self.peek() == "{":
                    body.children.append(self.block())
                elif self.maybe("("):
                    body.children += self.listed(")")
                else:
                    self.take()
            return body
        if self.peek() != "(":
            self.take()
        self.take("(")
        made = Node("function", children=[x for x in self.listed(")") if x.kind != "name"])
        made.children.append(self.block())
        return made

    def object(self) -> Node:
        out = Node("object")
        while not self.maybe("}"):
            if self.maybe(","):
                continue
            if self.maybe("..."):
                out.children.append(self.expression(1))
                continue
            if self.maybe("["):
                out.children += self.listed("]")
            else:
                self.take()
            if self.maybe(":"):
                out.children.append(self.expression(0))
            elif self.maybe("("):
                self.listed(")")
                out.children.append(self.block())
            elif self.peek() not in (",", "}"):  # get, set, async
                continue
        return out

    def postfix(self, left: Node, calls: bool = True) -> Node:
        while self.i < len(self.t):
            text = self.peek()
            if text in (".", "?."):
                self.take()
                if text == "?." and self.peek() in ("(", "["):
                    continue
                left = Node("member", self.take(), [left])
            elif text == "[":
                self.take()
                left = Node("index", children=[left, *self.listed("]")])
            elif text == "(" and calls:
                self.take()
                left = self.call(left, self.listed(")"))
            elif text in ("++", "--") and not self.t[self.i][2]:
                self.take()
            elif self.t[self.i][0] == "str" and self.t[self.i][1][0] == "`":
                self.take()
                left = self.call(left, [])
            else:
                break
        return left

    def call(self, callee: Node, args: list[Node]) -> Node:
        """A call's operator is its member's property, qualified under the known roots, or its name."""
        if callee.kind == "member":
            owner = callee.children[0]
            name = f"{owner.op}.{callee.op}" if owner.kind == "name" and owner.op in self.roots else callee.op
            return Node("call", name, [*([] if owner.kind == "name" else [callee]), *args])
        if callee.kind == "name":
            return Node("call", callee.op, args)
        return Node("call", "", [callee, *args])


# --- Python and HTML ----------------------------------------------------------------------


def _python(source: str, roots: frozenset[str]) -> Node:
    top = Node("program")
    stack: list[tuple[ast.AST, Node]] = [(ast.parse(source), top)]
    while stack:
        item, into = stack.pop()
        for child in ast.iter_child_nodes(item):
            if isinstance(child, (ast.Load, ast.Store, ast.Del, ast.operator, ast.cmpop, ast.unaryop, ast.boolop)):
                continue
            while isinstance(child, ast.Expr):
                child = child.value
            if isinstance(child, ast.Call):
                f, op = child.func, ""
                if isinstance(f, ast.Attribute):
                    op = f"{f.value.id}.{f.attr}" if isinstance(f.value, ast.Name) and f.value.id in roots else f.attr
                elif isinstance(f, ast.Name):
                    op = f.id
                made = Node("call", op)
            else:
                made = Node(type(child).__name__.lower())
            if isinstance(item, ast.Call) and child is item.func and isinstance(child, ast.Name):
                continue
            into.children.append(made)
            stack.append((child, made))
    return top


class _Html(HTMLParser):
    VOID = frozenset("area base br col embed hr img input link meta source track wbr".split())

    def __init__(self) -> None:
        super().__init__(convert_charrefs=True)
        self.top = Node("program")
        self.open = [self.top]

    def handle_starttag(self, tag: str, attrs) -> None:
        made = Node("element", tag)
        self.open[-1].children.append(made)
        if tag not in self.VOID:
            self.open.append(made)

    def handle_startendtag(self, tag: str, attrs) -> None:
        self.open[-1].children.append(Node("element", tag))

    def handle_endtag(self, tag: str) -> None:
        for i in range(len(self.open) - 1, 0, -1):
            if self.open[i].op == tag:
                del self.open[i:]
                return


def tree(source: str, lang: str, roots: frozenset[str] = frozenset()) -> Node:
    """The tree of a source; raises SyntaxError."""
    if lang in ("js", "javascript"):
        try:
            return JsParser(source, roots).program()
        except RecursionError as e:
            raise SyntaxError("nested too deeply") from e
    if lang in ("py", "python"):
        try:
            return _python(source, roots)
        except (ValueError, RecursionError, MemoryError) as e:
            raise SyntaxError(str(e)) from e
    if lang == "html":
        parser = _Html()
        parser.feed(source)
        parser.close()
        return parser.top
    raise ValueError(f"no parser for {lang}")


def flatten(top: Node) -> Iterator[tuple]:
    """Pre-order rows in the order of ``NODE_FIELDS``, without the top."""
    stack = [(c, -1, i, 0, (), top.children) for i, c in reversed(list(enumerate(top.children)))]
    n = 0
    while stack:
        node, parent, pos, depth, path, siblings = stack.pop()
        after = siblings[pos + 1] if pos + 1 < len(siblings) else None
        yield n, parent, pos, depth, node.kind, node.op, list(path), after.op if after is not None and after.calls else None
        inner = (*path, node.op) if node.calls else path
        stack += [(c, n, i, depth + 1, inner, node.children) for i, c in reversed(list(enumerate(node.children)))]
        n += 1


def nodes_of(source: str, lang: str, roots: frozenset[str] = frozenset()) -> list[tuple]:
    """Rows of one source, none if it does not parse."""
    try:
        return list(flatten(tree(source, lang, roots)))
    except SyntaxError:
        return []


def to_nodes(scripts: DataFrame, lang: str, roots: frozenset[str] = frozenset(), key: str = "script_id", source: str = "source") -> DataFrame:
    """Node rows of all scripts that parse (see ``NODE_DDL``)."""

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        names = ["script_id", *NODE_FIELDS]
        kinds = [pa.string(), *[pa.int32()] * 4, pa.string(), pa.string(), pa.list_(pa.string()), pa.string()]
        for batch in batches:
            for start in range(0, batch.num_rows, 64):
                part = batch.slice(start, 64)
                rows = [(k, *row) for k, s in zip(part.column(0).to_pylist(), part.column(1).to_pylist(), strict=True) for row in nodes_of(s or "", lang, roots)]
                cols = list(zip(*rows, strict=True)) or [[]] * len(names)
                yield pa.RecordBatch.from_arrays([pa.array(c, k) for c, k in zip(cols, kinds, strict=True)], names)

    return scripts.select(F.col(key).cast("string"), F.col(source).cast("string")).mapInArrow(run, NODE_DDL)


def check(scripts: DataFrame, lang: str, source: str = "source") -> DataFrame:
    """``scripts`` with ``parses`` and ``parse_error``; rows that do not parse are kept."""

    @F.udf("string")
    def error(text: str | None) -> str | None:
        try:
            tree(text or "", lang)
        except SyntaxError as e:
            return str(e)[:200] or "syntax error"
        return None

    return scripts.withColumn("parse_error", error(F.col(source))).withColumn("parses", F.col("parse_error").isNull())


_CODE_PARTS = {
    "js": re.compile(r"('(?:\\.|[^'\\\n])*'|\"(?:\\.|[^\"\\\n])*\"|`(?:\\.|[^`\\])*`)|//[^\n]*|/\*.*?(?:\*/|\Z)", re.S),
    "py": re.compile(r"('''.*?'''|\"\"\".*?\"\"\"|'(?:\\.|[^'\\\n])*'|\"(?:\\.|[^\"\\\n])*\")|#[^\n]*", re.S),
}


def strip_code(text: str, lang: str) -> str:
    """The text without comments; strings are left alone."""
    return _CODE_PARTS[lang].sub(lambda m: m[1] or "", text)


def strip_comments(col: Column, lang: str) -> Column:
    """Comments out: column expressions for HTML, a tokenizer for code."""
    if lang == "html":
        return F.regexp_replace(col, r"(?s)<!--.*?-->", "")
    return F.udf(lambda s: None if s is None else strip_code(s, lang), "string")(col)


def clean_html(col: Column) -> Column:
    """Text of a page: comments, scripts, styles and tags out, blanks collapsed."""
    bare = F.regexp_replace(strip_comments(col, "html"), r"(?s)<(script|style)[^>]*>.*?</(script|style)>", " ")
    return F.trim(F.regexp_replace(F.regexp_replace(bare, "<[^>]*>", " "), r"[ \t\r\n]+", " "))
