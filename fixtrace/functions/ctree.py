"""Syntax trees of C statements without compiling: parse, expand calls, normalise, flatten.

A tree is a nested tuple (label, child, ...).  The grammar covers statements and expressions of C functions;
anything else raises ``Unparsed``, and callers then have no tree rather than a wrong one.
"""

from __future__ import annotations

import functools
import re
from bisect import bisect_left

LEXEMES = re.compile(
    r"\s+|/\*.*?\*/|//[^\n]*|(?P<num>0[xX][0-9a-fA-F]+[uUlL]*|\d+\.?\d*[uUlLfF]*)|(?P<str>\"(?:\\.|[^\"\\])*\"|'(?:\\.|[^'\\])*')"
    r"|(?P<id>[A-Za-z_]\w*)|(?P<op><<=|>>=|\.\.\.|->|\+\+|--|<<|>>|<=|>=|==|!=|&&|\|\||[-+*/%&|^]=|[-+*/%&|^~!<>=?:;,.(){}\[\]])",
    re.S,
)
BINARY = {"*": 10, "/": 10, "%": 10, "+": 9, "-": 9, "<<": 8, ">>": 8, "<": 7, ">": 7, "<=": 7, ">=": 7, "==": 6, "!=": 6, "&": 5, "^": 4, "|": 3, "&&": 2, "||": 1}
ASSIGN = {"=", "+=", "-=", "*=", "/=", "%=", "&=", "|=", "^=", "<<=", ">>="}
TYPES = {"void", "char", "short", "int", "long", "float", "double", "signed", "unsigned", "const", "static", "struct", "size_t", "ssize_t", "bool", "register", "volatile", "inline", "enum", "union"}
COMMUTE = {"+", "*", "==", "!=", "&&", "||", "&", "|", "^"}
RULES = frozenset({"cond", "loop", "commute", "compare"})


class Unparsed(ValueError):
    """The text lies outside the grammar."""


def plain_numbers(text: str) -> str:
    """The text with every whole number 1: tokens stay of the same kinds, so what a reader of kinds and names sees is the same."""
    return re.sub(r"\b[0-9]+\b", "1", text)


def lex(text: str) -> list[tuple[str, str, int]]:
    """(kind, lexeme, line number from 1)."""
    out, at, line = [], 0, 1
    while at < len(text):
        m = LEXEMES.match(text, at)
        if not m or m.end() == at:
            raise Unparsed(f"at {at}: {text[at : at + 20]!r}")
        if m.lastgroup:
            out.append((m.lastgroup, m.group(), line))
        line += m.group().count("\n")
        at = m.end()
    return out


class Parser:
    def __init__(self, text: str):
        self.tokens, self.at, self.depth = lex(text), 0, 0
        self.spans: list[tuple[int, int, tuple]] = []  # first line, last line and tree of every statement

    def peek(self, k: int = 0) -> str:
        return self.tokens[self.at + k][1] if self.at + k < len(self.tokens) else ""

    def kind(self, k: int = 0) -> str:
        return self.tokens[self.at + k][0] if self.at + k < len(self.tokens) else ""

    def take(self, want: str | None = None) -> str:
        got = self.peek()
        if not got or want is not None and got != want:
            raise Unparsed(f"{want or 'a token'} expected, not {got or 'the end'}")
        self.at += 1
        return got

    def has(self, want: str) -> bool:
        if self.peek() == want:
            self.at += 1
            return True
        return False

    def program(self) -> tuple:
        out = []
        while self.at < len(self.tokens):
            out.append(self.statement())
        return ("block", *out)

    def statement(self) -> tuple:
        self.depth += 1
        if self.depth > 200:
            raise Unparsed("nested too deeply")
        try:
            first = self.tokens[self.at][2] if self.at < len(self.tokens) else 0
            tree = self._statement()
            self.spans.append((first, self.tokens[self.at - 1][2], tree))
            return tree
        finally:
            self.depth -= 1

    def _statement(self) -> tuple:
        word = self.peek()
        if word == "{":
            self.take()
            out = []
            while not self.has("}"):
                out.append(self.statement())
            return ("block", *out)
        if self.has(";"):
            return ("empty",)
        if self.has("if"):
            self.take("(")
            test = self.expression()
            self.take(")")
            then = self.statement()
            return ("if", test, then, self.statement()) if self.has("else") else ("if", test, then)
        if self.has("while"):
            self.take("(")
            test = self.expression()
            self.take(")")
            return ("while", test, self.statement())
        if self.has("do"):
            body = self.statement()
            self.take("while")
            self.take("(")
            test = self.expression()
            self.take(")")
            self.take(";")
            return ("do", body, test)
        if self.has("for"):
            self.take("(")
            first = ("empty",) if self.has(";") else self.simple()
            test = ("id:1",) if self.peek() == ";" else self.expression()
            self.take(";")
            step = ("empty",) if self.peek() == ")" else self.comma()
            self.take(")")
            return ("for", first, test, step, self.statement())
        if self.has("switch"):
            return self.switch()
        if word in ("return", "goto"):
            self.take()
            out = (word,) if self.peek() == ";" else (word, self.comma())
            self.take(";")
            return out
        if word in ("break", "continue"):
            self.take()
            self.take(";")
            return (word,)
        return self.simple()

    def switch(self) -> tuple:
        self.take("(")
        test = self.expression()
        self.take(")")
        self.take("{")
        groups: list[tuple[list, list]] = []
        while not self.has("}"):
            labels = []
            while self.peek() in ("case", "default"):
                if self.take() == "case":
                    labels.append(self.expression())
                else:
                    labels.append(None)
                self.take(":")
            body = []
            while self.peek() not in ("case", "default", "}"):
                body.append(self.statement())
            groups.append((labels, body))
        return ("switch", test, *(("case", ("labels", *(x or ("default",) for x in labels)), ("block", *body)) for labels, body in groups))

    def simple(self) -> tuple:
        """A declaration or expression statement with its semicolon."""
        if self.peek() in TYPES or self.kind() == "id" and self.kind(1) == "id" or self.kind() == "id" and self.peek(1) == "*" and self.kind(2) == "id" and self.peek(3) in ("=", ";", ","):
            return self.declaration()
        out = self.comma()
        self.take(";")
        return out

    def declaration(self) -> tuple:
        words = []
        while self.peek() in TYPES or self.kind() == "id" and (self.kind(1) == "id" or self.peek(1) == "*"):
            words.append(self.take())
        out = []
        while True:
            stars = 0
            while self.has("*"):
                stars += 1
            if self.kind() != "id":
                raise Unparsed("a name expected")
            name: tuple = (f"id:{self.take()}",)
            while self.has("["):
                name = ("index", name, ("empty",) if self.peek() == "]" else self.expression())
                self.take("]")
            kind = (f"type:{' '.join(words)}{'*' * stars}",)
            if self.has("="):
                out.append(("decl", kind, ("=", name, self.initial())))
            else:
                out.append(("decl", kind, name))
            if not self.has(","):
                break
        self.take(";")
        return out[0] if len(out) == 1 else ("block", *out)

    def initial(self) -> tuple:
        if not self.has("{"):
            return self.assignment()
        out = []
        while not self.has("}"):
            out.append(self.initial())
            self.has(",")
        return ("list", *out)

    def comma(self) -> tuple:
        out = [self.assignment()]
        while self.has(","):
            out.append(self.assignment())
        return out[0] if len(out) == 1 else ("block", *out)

    def expression(self) -> tuple:
        return self.assignment()

    def assignment(self) -> tuple:
        left = self.ternary()
        if self.peek() in ASSIGN:
            return (self.take(), left, self.assignment())
        return left

    def ternary(self) -> tuple:
        test = self.binary(1)
        if self.has("?"):
            yes = self.assignment()
            self.take(":")
            return ("?", test, yes, self.assignment())
        return test

    def binary(self, least: int) -> tuple:
        left = self.unary()
        while BINARY.get(self.peek(), 0) >= least:
            op = self.take()
            left = (op, left, self.binary(BINARY[op] + 1))
        return left

    def unary(self) -> tuple:
        self.depth += 1
        if self.depth > 200:
            raise Unparsed("nested too deeply")
        try:
            if self.peek() in ("!", "~", "-", "+", "*", "&", "++", "--"):
                return (f"u{self.take()}", self.unary())
            if self.peek() == "sizeof":
                self.take()
                return ("sizeof", self.unary())
            if self.peek() == "(" and (self.peek(1) in TYPES or self.kind(1) == "id" and self.peek(2) == "*" and self.peek(3) == ")"):
                self.take()
                words = []
                while self.peek() != ")":
                    words.append(self.take())
                self.take(")")
                return ("cast", (f"type:{' '.join(words)}",), self.unary()) if self.peek() not in (")", ";", ",", "") else (f"type:{' '.join(words)}",)
            return self.postfix()
        finally:
            self.depth -= 1

    def postfix(self) -> tuple:
        kind = self.kind()
        if self.has("("):
            out = self.comma()
            self.take(")")
        elif kind in ("id", "num", "str"):
            out = (f"{'id' if kind == 'id' else kind}:{self.take()}",)
        else:
            raise Unparsed(f"an operand expected, not {self.peek() or 'the end'}")
        while True:
            if self.has("("):
                args = []
                while not self.has(")"):
                    args.append(self.assignment())
                    if self.peek() != ")":
                        self.take(",")
                out = ("call", out, *args)
            elif self.has("["):
                out = ("index", out, self.expression())
                self.take("]")
            elif self.peek() in (".", "->"):
                out = (self.take(), out, (f"id:{self.take()}",))
            elif self.peek() in ("++", "--"):
                out = (f"p{self.take()}", out)
            else:
                return out


def parse(text: str) -> tuple:
    """The tree of some statements."""
    try:
        return Parser(text).program()
    except RecursionError:
        raise Unparsed("nested too deeply") from None


def subtrees(text: str, lines: set[int]) -> list[tuple]:
    """For each wanted line the smallest statement that covers it, each once, in order."""
    parser = Parser(text)
    parser.program()
    out = []
    for line in sorted(lines):
        covering = [(last - first, -k, tree) for k, (first, last, tree) in enumerate(parser.spans) if first <= line <= last]
        if covering and (found := min(covering)[2]) not in out:
            out.append(found)
    return out


def definitions(rows) -> dict[str, tuple[list[str], tuple]]:
    """name to (parameters, body tree) from (name, parameters, body) rows; bodies that do not parse are left out."""
    out = {}
    for name, params, body in rows:
        try:
            out[name] = (list(params), parse(body))
        except Unparsed:
            continue
    return out


def substitute(tree: tuple, values: dict[str, tuple]) -> tuple:
    if len(tree) == 1:
        return values.get(tree[0], tree)
    return (tree[0], *(substitute(x, values) for x in tree[1:]))


def expand(tree: tuple, defs: dict, depth: int = 1, inside: frozenset = frozenset()) -> tuple:
    """Calls of known functions and macros replaced by their bodies; a name is never expanded inside itself."""
    if len(tree) == 1:
        return tree
    parts = tuple(expand(x, defs, depth, inside) for x in tree[1:])
    if tree[0] == "call" and depth > 0 and len(parts[0]) == 1 and parts[0][0].startswith("id:"):
        name = parts[0][0][3:]
        if name in defs and name not in inside and len(defs[name][0]) == len(parts) - 1:
            params, body = defs[name]
            body = substitute(body, {f"id:{p}": v for p, v in zip(params, parts[1:], strict=True)})
            body = expand(body, defs, depth - 1, inside | {name})
            return body[1] if body[0] == "block" and len(body) == 2 else body
    return (tree[0], *parts)


def _text(tree: tuple) -> str:
    return "(" + " ".join([tree[0], *map(_text, tree[1:])]) + ")" if len(tree) > 1 else tree[0].partition(":")[2] or tree[0]


def _listed(tree: tuple) -> tuple:
    """Statements of a body; a block of one statement is that statement."""
    flat = []
    for x in tree[1:] if tree[0] == "block" else (tree,):
        flat.extend(x[1:] if x[0] == "block" else [x])
    flat = [x for x in flat if x != ("empty",)]
    return flat[0] if len(flat) == 1 else ("block", *flat)


def normalize(tree: tuple, rules=RULES) -> tuple:
    """The normal form under some of the rules: cond, loop, commute, compare."""
    label, parts = tree[0], tuple(normalize(x, rules) for x in tree[1:])
    if label == "switch" and "cond" in rules:
        return _chain(parts[0], parts[1:], rules)
    if label in ASSIGN and "cond" in rules and parts[1][0] == "?":
        _, test, yes, no = parts[1]
        return normalize(("if", test, (label, parts[0], yes), (label, parts[0], no)), rules)
    if label == "if" and len(parts) == 3 and "cond" in rules and parts[2][0] == "=" and parts[2][1] == parts[2][2]:
        return normalize(("if", *parts[:2]), rules)  # the other branch assigns a variable to itself
    if label == "for" and "loop" in rules:
        first, test, step, body = parts
        return _listed(("block", first, ("while", test, _listed(("block", body, step)))))
    if label == "do" and "loop" in rules:
        return _listed(("block", parts[0], ("while", parts[1], parts[0])))
    if label in COMMUTE and len(parts) == 2 and "commute" in rules:
        chain: list[tuple] = []
        for x in parts:
            chain.extend(x[1:] if x[0] == label and label not in ("==", "!=") else [x])
        return (label, *sorted(chain, key=_text))
    if label in ("<", "<=", ">", ">=") and len(parts) == 2 and "compare" in rules:
        label, parts = (">" + label[1:], parts[::-1]) if label[0] == "<" else (label, parts)
        if parts[1][0] == "-" and len(parts[1]) == 3:  # a term taken away on the right is added on the left
            return (label, normalize(("+", parts[0], parts[1][2]), rules), parts[1][1])
        return (label, *parts)
    if label in ("block", "if", "while"):
        if label == "block":
            return _listed((label, *parts))
        return (label, parts[0], *(_listed(x) for x in parts[1:]))
    if label in ("u++", "p++", "u--", "p--"):
        return ("++" if "++" in label else "--", *parts)
    return (label, *parts)


def _chain(test: tuple, cases: tuple, rules) -> tuple:
    """If-else chain of a switch; a group that falls through with a body of its own keeps the switch as it is."""
    arms, other, ahead = [], None, []
    for k, (_, labels, body) in enumerate(cases):
        statements = list(body[1:]) if body[0] == "block" else [body]
        ahead += labels[1:]
        if not statements and k < len(cases) - 1:
            continue
        ends = statements and statements[-1][0] in ("break", "return", "goto", "continue")
        if not ends and k < len(cases) - 1:
            return ("switch", test, *cases)
        if statements and statements[-1] == ("break",):
            statements.pop()
        done = _listed(("block", *statements))
        if ("default",) in ahead:
            other = done
        else:
            equal = [normalize(("==", test, x), rules) for x in ahead]
            arms.append((equal[0] if len(equal) == 1 else normalize(("||", *equal[:2]), rules) if len(equal) == 2 else ("||", *sorted(equal, key=_text)), done))
        ahead = []
    out = other
    for cond, done in reversed(arms):
        out = ("if", cond, done) if out is None else ("if", cond, done, out)
    return out if out is not None else ("empty",)


def inorder(tree: tuple) -> list[str]:
    """Labels in order: the first child, the node, the other children."""
    if len(tree) == 1:
        return [tree[0]]
    out = inorder(tree[1])
    out.append(tree[0])
    for x in tree[2:]:
        out += inorder(x)
    return out


def labels(text: str, defs: dict | None = None, depth: int = 1, rules=RULES) -> list[str] | None:
    """The flattened normal form of some statements; null where they do not parse."""
    try:
        return inorder(normalize(expand(parse(text), defs or {}, depth), rules))
    except (Unparsed, RecursionError):
        return None


@functools.lru_cache(maxsize=200_000)
def _point(name: str) -> str:
    h = 2166136261
    for b in name.encode():
        h = (h ^ b) * 16777619 & 0xFFFFFFFF
    h = (h ^ h >> 15) * 0x2C1B3C6D & 0xFFFFFFFF
    return chr(0x10000 + (h ^ h >> 13) % 0xFFFFE)


def code_points(names: list[str]) -> str:
    """One code point for each label.  Fixed by the label's text alone (31-bit hash folded past the surrogates),
    so sequences made in different tasks compare; two labels share a point with odds of one in a million."""
    return "".join(map(_point, names))


#: Words that the grammar or a tree's own labels tell apart from other names; 1 is the test of a loop without one.
WORDS = frozenset(TYPES | {"if", "else", "while", "for", "do", "switch", "case", "default", "return", "goto", "break", "continue", "sizeof", "empty", "block", "labels", "list", "call", "index", "cast", "decl", "1"})
WORD = re.compile(r"([A-Za-z_][A-Za-z0-9_]*|[0-9]+)")
#: Strings, and numbers other than plain whole ones, whose order beside others is not that of their words.
ODD = re.compile(r"[\"']|[0-9]\.|\.[0-9]|(?<![A-Za-z0-9_])[0-9]+[A-Za-z_]")
SPACE = re.compile(r"\s+|/\*.*?\*/|//[^\n]*", re.S)


class Shapes:
    """``labels`` as code points for many texts with the same definitions; texts of one shape are parsed once.

    The normal form depends on names and whole numbers only by which are equal, their order, their order among the
    words of the grammar and of the definitions, and those words themselves.  So a text whose other words have the same
    order and the same places among these words has the same labels but for the words put in.  Texts with other
    constants, and such whose types are names of their own, are parsed each.
    """

    def __init__(self, rows, depth: int = 1, rules=RULES, held: int = 50_000):
        self.defs, self.depth, self.rules, self.held = definitions(rows), depth, rules, held
        bodies = [x for name, params, body in rows for x in (name, *params, body)]
        self.fixed = WORDS.union(*(WORD.findall(x) for x in bodies)) if bodies else WORDS
        self.ordered = sorted(self.fixed)
        self.odd = any(not x.isascii() or ODD.search(x) for x in bodies)
        self.known: dict[tuple, list | None | bool] = {}
        self.place = functools.lru_cache(maxsize=200_000)(lambda word: bisect_left(self.ordered, word))

    def codes(self, text: str) -> str | None:
        found = None
        if not self.odd and text.isascii() and not ODD.search(text):
            parts = WORD.split(SPACE.sub(" ", text))
            free = sorted(set(parts[1::2]) - self.fixed)
            rank = {w: k for k, w in enumerate(free)}
            key = (tuple(parts[::2]), tuple(rank.get(w, w) for w in parts[1::2]), tuple(map(self.place, free)), tuple(w[0] < "A" for w in free))
            if key not in self.known:
                if len(self.known) >= self.held:
                    self.known.clear()
                self.known[key] = self._template(text, rank)
            found = self.known[key]
            if found is None:
                return None
        if not found:
            names = labels(text, self.defs, self.depth, self.rules)
            return None if names is None else code_points(names)
        return "".join(x if type(x) is str else _point(x[0] + free[x[1]]) for x in found)

    def _template(self, text: str, rank: dict[str, int]) -> list | None | bool:
        """Code points, and (prefix, rank) for the words to put in; null where it does not parse, false where no other text tells."""
        names = labels(text, self.defs, self.depth, self.rules)
        if names is None:
            return None
        out: list = []
        for name in names:
            head, mark, word = name.partition(":")
            if head == "type" and any(w in rank for w in WORD.findall(word)):
                return False
            out.append((head + mark, rank[word]) if mark and word in rank else _point(name))
        return out


def calls(tree: tuple) -> list[str]:
    """Names called anywhere in a tree."""
    out = [tree[1][0][3:]] if tree[0] == "call" and len(tree[1]) == 1 and tree[1][0].startswith("id:") else []
    for x in tree[1:]:
        out += calls(x)
    return out


def operators(tree: tuple) -> list[str]:
    """Arithmetic operators anywhere in a tree, compound assignments by their operator."""
    found = {"+": "+", "*": "*", "<<": "<<", "+=": "+", "*=": "*", "<<=": "<<"}.get(tree[0])
    out = [found] if found and len(tree) > 2 else []
    for x in tree[1:]:
        out += operators(x)
    return out
