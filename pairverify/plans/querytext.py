"""A subset of SPARQL as text and as a plain structure: parse, render, canonical form, questions, and wrong near-twins.

Terms are strings as they stand in the text: <iri>, [label], ?variable, _:blank, "literal" or a number. A query is a
dict: form (select, ask, count), distinct, vars, patterns (triples), filters ((left, op, right), where right may be a query of its own), order ((var,
ascending) or None), limit, group, fn. Parsing and printing are each other's inverse.
"""

from __future__ import annotations

import copy
import hashlib
import re

TOKEN = re.compile(r'<[^>]*>|\[[^\]]*\]|"(?:[^"\\]|\\.)*"|\?\w+|_:\w+|[A-Za-z]+|-?\d+(?:\.\d+)?|[<>!]?=|[{}()<>.*]')
PREFIX = re.compile(r"\s*PREFIX\s+(\w+):\s*<([^>]*)>", re.I)
FUNCTIONS = ("COUNT", "SUM", "AVG", "MIN", "MAX")


def parse(text: str) -> dict:
    names = {}
    while m := PREFIX.match(text):
        names[m[1]] = m[2]
        text = text[m.end() :]
    for short, long in names.items():
        text = re.sub(rf"(?<![\w<]){short}:([\w/]+)", lambda m, long=long: f"<{long}{m[1]}>", text)
    words, at = TOKEN.findall(text), 0

    def take(want: str | None = None) -> str:
        nonlocal at
        if at >= len(words) or want and words[at].upper() != want:
            raise ValueError(f"expected {want or 'more'} at {' '.join(words[at : at + 3]) or 'the end'}")
        at += 1
        return words[at - 1]

    def peek() -> str:
        return words[at].upper() if at < len(words) else ""

    def one(nested: bool = False) -> dict:
        q = {"form": "select", "distinct": False, "vars": [], "patterns": [], "filters": [], "order": None, "limit": None, "group": [], "fn": None}
        if peek() == "ASK":
            take()
            q["form"] = "ask"
        else:
            take("SELECT")
            while peek() not in ("WHERE", "{"):
                if peek() == "DISTINCT":
                    take()
                    q["distinct"] = True
                elif peek() == "(":
                    take()
                    fn = take().upper()
                    if fn not in FUNCTIONS:
                        raise ValueError(f"unknown function {fn}")
                    take("(")
                    inner = peek() == "DISTINCT"
                    if inner:
                        take()
                    var = take()
                    take(")")
                    take("AS")
                    q["form"], q["fn"] = "count" if fn == "COUNT" else "aggregate", {"fn": fn, "var": var, "distinct": inner, "as": take()}
                    take(")")
                else:
                    q["vars"].append(take())
        if peek() == "WHERE":
            take()
        take("{")
        while peek() != "}":
            if peek() == "FILTER":
                take()
                take("(")
                left, op = take(), take()
                right = take()
                if right == "(":  # a query of its own that gives one number
                    right = one(nested=True)
                    take(")")
                q["filters"].append((left, op, right))
                take(")")
            else:
                q["patterns"].append((take(), take(), take()))
            if peek() == ".":
                take()
        take("}")
        while at < len(words) and not (nested and peek() == ")"):
            word = take().upper()
            if word == "GROUP":
                take("BY")
                while peek().startswith("?"):
                    q["group"].append(take())
            elif word == "ORDER":
                take("BY")
                way = take().upper() if peek() in ("ASC", "DESC") else "ASC"
                inner = peek() == "("
                if inner:
                    take()
                q["order"] = (take(), way == "ASC")
                if inner:
                    take()
            elif word == "LIMIT":
                q["limit"] = int(take())
            else:
                raise ValueError(f"unknown clause {word}")
        return q

    return one()


def render(q: dict) -> str:
    if q["form"] == "ask":
        head = "ASK"
    else:
        parts = (["DISTINCT"] if q["distinct"] else []) + q["vars"]
        if f := q["fn"]:
            parts.append(f"({f['fn']}({'DISTINCT ' if f['distinct'] else ''}{f['var']}) AS {f['as']})")
        head = "SELECT " + " ".join(parts)
    body = [" ".join(p) + " ." for p in q["patterns"]] + [f"FILTER({a} {op} {'(' + render(b) + ')' if isinstance(b, dict) else b})" for a, op, b in q["filters"]]
    tail = f" GROUP BY {' '.join(q['group'])}" if q["group"] else ""
    if q["order"]:
        tail += f" ORDER BY {'ASC' if q['order'][1] else 'DESC'}({q['order'][0]})"
    return f"{head} WHERE {{ {' '.join(body)} }}{tail}" + (f" LIMIT {q['limit']}" if q["limit"] is not None else "")


def _free(term: str) -> bool:
    return term[:1] == "?" or term[:2] == "_:"


def canonical(q: dict) -> str:
    """Text with variables renamed and patterns sorted, the same for queries that differ in these only."""
    links = {}
    for k, p in enumerate(q["patterns"]):
        for s, t in enumerate(p):
            if _free(t):
                links.setdefault(t, []).append((k, s))
    colour = {t: hashlib.md5(repr((t in q["vars"], [q["vars"].index(t)] if t in q["vars"] else [], bool(q["fn"]) and q["fn"]["var"] == t, bool(q["order"]) and q["order"][0] == t)).encode()).hexdigest() for t in links}
    for _ in range(len(links) + 1):
        colour = {t: hashlib.md5((c + repr(sorted((s, [colour.get(x, x) for x in q["patterns"][k]]) for k, s in links[t]))).encode()).hexdigest() for t, c in colour.items()}
    order = sorted(links, key=lambda t: colour[t])
    name = {t: f"?v{k}" for k, t in enumerate(order)}
    swap = lambda t: name.get(t, t)
    c = copy.deepcopy(q)
    c["patterns"] = sorted(tuple(map(swap, p)) for p in q["patterns"])
    c["filters"] = sorted((swap(a), op, f"({canonical(b)})" if isinstance(b, dict) else swap(b)) for a, op, b in q["filters"])
    c["vars"], c["group"] = [swap(v) for v in q["vars"]], [swap(v) for v in q["group"]]
    c["order"] = (swap(q["order"][0]), q["order"][1]) if q["order"] else None
    if c["fn"]:
        c["fn"] |= {"var": swap(c["fn"]["var"]), "as": "?n"}
    return render(c)


def canonical_sha(text: str) -> str:
    return hashlib.sha256(canonical(parse(text)).encode()).hexdigest()


# -- questions ---------------------------------------------------------------------------------------------------

COMPARE = {">": "is greater than", "<": "is less than", ">=": "is at least", "<=": "is at most", "=": "is equal to", "!=": "differs from"}
FLIPPED = {">": "<", "<": ">", ">=": "<=", "<=": ">=", "=": "!=", "!=": "="}


#: Wordings; training questions take the first three, the last one is that of people and never trained on.
FAMILIES = 4


def _say(term: str) -> str:
    if term[:1] in "[<":
        return term[1:-1]
    if term[:1] == '"':
        return term[1:-1]
    return f"some {term[2:]}" if term[:2] == "_:" else term[1:].upper() if term[:1] == "?" else term


def _phrase(p: tuple, family: int) -> str:
    h, r, t = map(_say, p)
    return (f"{t} is the {r} of {h}", f"{h} has the {r} {t}", f"the {r} for {h} is {t}", f"{h}'s {r} is {t}")[family % FAMILIES]


def question(q: dict, family: int = 0) -> str:
    """An English question with the query's meaning, in one of four wordings."""
    said = [_phrase(p, family) for p in q["patterns"]] + [f"{_say(a)} {COMPARE[op]} {_say(b)}" for a, op, b in q["filters"]]
    where = " and ".join(said)
    what = " and ".join(map(_say, q["vars"]))
    tail = ""
    if q["order"]:
        tail = f", {'first' if q['limit'] else 'sorted'} by the {'lowest' if q['order'][1] else 'highest'} {_say(q['order'][0])}" + (f", only {q['limit']}" if q["limit"] else "")
    if q["form"] == "ask":
        return (f"Is it true that {where}?", f"Does it hold that {where}?", f"Can it be said that {where}?", f"Do we know that {where}?")[family % FAMILIES]
    if q["form"] == "count":
        v = ("different " if q["fn"]["distinct"] else "") + _say(q["fn"]["var"])
        return (f"How many {v} are there such that {where}?", f"What is the number of {v} for which {where}?", f"Count the {v} where {where}.", f"Tell me how many {v} exist if {where}.")[family % FAMILIES]
    if q["form"] == "aggregate":
        what = f"{q['fn']['fn'].lower()} of {_say(q['fn']['var'])}" + (f" for each {' and '.join(map(_say, q['group']))}" if q["group"] else "")
    return (f"What is {what} such that {where}{tail}?", f"Which {what} satisfy that {where}{tail}?", f"Give {what} where {where}{tail}.", f"Tell me {what} if {where}{tail}.")[family % FAMILIES]


def understand(text: str) -> dict | None:
    """The query behind a question of the wordings above, with labels for identifiers; None for anything else."""
    m = re.match(r"(Is it true that|Does it hold that|Can it be said that|How many|What is the number of|Count the|What is|Which|Give) (.*)[?.]$", text)
    if not m:
        return None
    lead, rest = m[1], m[2]
    q = {"form": "select", "distinct": False, "vars": [], "patterns": [], "filters": [], "order": None, "limit": None, "group": [], "fn": None}
    back = lambda s: f"_:{s[5:]}" if re.fullmatch(r"some \w+", s) else f"?{s.lower()}" if re.fullmatch(r"[A-Z]\w{0,2}", s) and s.isupper() else s if re.fullmatch(r"-?\d+(\.\d+)?", s) else f"[{s}]"
    if lead in ("Is it true that", "Does it hold that", "Can it be said that"):
        q["form"] = "ask"
    else:
        cut = re.split(r" are there such that | for which | such that | satisfy that | where ", rest, maxsplit=1)
        if len(cut) != 2:
            return None
        what, rest = cut
        if m2 := re.search(r", (?:first|sorted) by the (lowest|highest) (\w+)(?:, only (\d+))?$", rest):
            q["order"], q["limit"] = (back(m2[2]), m2[1] == "lowest"), int(m2[3]) if m2[3] else None
            rest = rest[: m2.start()]
        if lead in ("How many", "What is the number of", "Count the"):
            distinct = what.startswith("different ")
            q["form"], q["fn"] = "count", {"fn": "COUNT", "var": back(what.removeprefix("different ")), "distinct": distinct, "as": "?n"}
        elif m2 := re.match(r"(sum|avg|min|max) of (\w+)(?: for each (.*))?$", what):
            q["form"], q["fn"] = "aggregate", {"fn": m2[1].upper(), "var": back(m2[2]), "distinct": False, "as": "?n"}
            q["group"] = [back(v) for v in m2[3].split(" and ")] if m2[3] else []
            q["vars"] = list(q["group"])
        else:
            q["vars"] = [back(v) for v in what.split(" and ")]
    for part in rest.split(" and "):
        for op, words in COMPARE.items():
            if f" {words} " in part and " the " not in part:
                a, b = part.split(f" {words} ", 1)
                q["filters"].append((back(a), op, back(b)))
                break
        else:
            if m2 := re.fullmatch(r"the (.+) for (.+) is (.+)", part):
                q["patterns"].append((back(m2[2]), f"[{m2[1]}]", back(m2[3])))
            elif m2 := re.fullmatch(r"(.+) is the (.+) of (.+)", part):
                q["patterns"].append((back(m2[3]), f"[{m2[2]}]", back(m2[1])))
            elif m2 := re.fullmatch(r"(.+?) has the (.+?) (some \w+|\S+|[A-Z#].*)", part):
                q["patterns"].append((back(m2[1]), f"[{m2[2]}]", back(m2[3])))
            else:
                return None
    return q


# -- wrong near-twins --------------------------------------------------------------------------------------------


def _invert(q):
    k = next((k for k, p in enumerate(q["patterns"]) if p[0] != p[2]), None)
    if k is not None:
        h, r, t = q["patterns"][k]
        q["patterns"][k] = (t, r, h)


def _drop_blank(q):
    kept = [p for p in q["patterns"] if not any(t[:2] == "_:" for t in p)]
    blank = [p for p in q["patterns"] if any(t[:2] == "_:" for t in p)]
    if len(blank) > 1:  # the statement's parts are said of its subject at once
        subject = next((p[0] for p in blank if p[0][:2] != "_:"), blank[0][0])
        q["patterns"] = kept + [(subject, p[1], p[2]) for p in blank if p[2][:2] != "_:"]


def _drop_condition(q):
    if q["filters"]:
        q["filters"].pop()
    elif len(q["patterns"]) > 1:
        q["patterns"].pop()


def _recursion(q):
    v = next((t for p in q["patterns"] for t in p if _free(t)), None)
    if v:
        q["patterns"].append((v, q["patterns"][-1][1], v))


def _add(q):
    v = next((t for p in q["patterns"] for t in p if _free(t)), q["patterns"][0][0])
    q["patterns"].append((v, "[country of origin]", "[Atlantis]"))


def _swap(q):
    named = [t for p in q["patterns"] for t in (p[0], p[2]) if not _free(t)]
    if len(set(named)) > 1:
        a, b = named[0], next(t for t in named if t != named[0])
        q["patterns"] = [tuple(b if t == a else a if t == b else t for t in p) for p in q["patterns"]]
    elif named:
        q["patterns"] = [tuple("[Nowhere]" if t == named[0] else t for t in p) for p in q["patterns"]]


def _literal(q):
    if q["filters"]:
        a, op, b = q["filters"][0]
        q["filters"][0] = (a, FLIPPED[op], b)
    elif q["limit"]:
        q["limit"] += 1
    elif q["order"]:
        q["order"] = (q["order"][0], not q["order"][1])
    else:
        _swap(q)


def _uncount(q):
    if q["form"] == "count":
        q["form"], q["vars"], q["fn"] = "select", [q["fn"]["var"]], None
    elif q["form"] == "select" and q["vars"]:
        q["form"], q["fn"], q["vars"] = "count", {"fn": "COUNT", "var": q["vars"][0], "distinct": False, "as": "?n"}, []


WRONG = {"invert_relation": _invert, "flatten_statement": _drop_blank, "drop_qualifier": _drop_blank, "drop_condition": _drop_condition, "variable_recursion": _recursion, "add_statement": _add, "swap_entities": _swap, "change_literal": _literal, "count_or_list": _uncount}
#: Kinds that keep the meaning.
RIGHT = ("alias_from_description", "bad_grammar")


def wrong_twin(q: dict, kind: str) -> dict | None:
    """A query of another meaning with the same terms, or None where the kind changes nothing here."""
    twin = copy.deepcopy(q)
    WRONG[kind](twin)
    return twin if twin != q and canonical(twin) != canonical(q) else None


#: Names that are a word, the hash sign and a number, standing by themselves; and such a name from its hash sign on.
NUMBERED = re.compile(r"((?<![\w#])(?<![\w#][-.])[A-Za-z]+#\d+(?![\w#]|[-.]\w))")
NUMBER = re.compile(r"#\d+(?![\w#]|[-.]\w)")
LETTERS = frozenset("ABCDEFGHIJKLMNOPQRSTUVWXYZabcdefghijklmnopqrstuvwxyz")


def bare_numbers(text: str, seen: dict[str, str] | None = None) -> tuple[str, dict[str, str]]:
    """The text with its numbered names counted from 1 on, and what each stands for; equal names (but for case) share a number.

    seen: names met before by their lower case, with their numbers; new ones are put in.
    """
    seen, back = {} if seen is None else seen, {}
    if "#" not in text:
        return text, back
    out, last = [], 0
    word = lambda c: c.isalnum() or c in "_#"
    for m in NUMBER.finditer(text):  # NUMBERED, searched from its rarest character
        at = start = m.start()
        while start and text[start - 1] in LETTERS:
            start -= 1
        if start == at or start and (word(text[start - 1]) or start > 1 and text[start - 1] in "-." and word(text[start - 2])):
            continue
        name = text[start : m.end()]
        short = f"{text[start:at]}#{seen.setdefault(name.lower(), str(len(seen) + 1))}"
        back[short] = name
        out += text[last:start], short
        last = m.end()
    return "".join(out) + text[last:], back


def full_numbers(text: str, back: dict[str, str]) -> str:
    return NUMBERED.sub(lambda m: back.get(m[0], m[0]), text) if back else text


class Asker:
    """Twins and questions of query texts, worked out once for texts that differ in numbers of names only."""

    def __init__(self, most: int = 1 << 16):
        self.known, self.most = {}, most

    def _once(self, key: tuple, make):
        if key not in self.known:
            if len(self.known) >= self.most:
                self.known.clear()
            self.known[key] = make()
        return self.known[key]

    def _twin(self, bare: str, kind: str) -> dict | None:
        return self._once((bare, kind), lambda: wrong_twin(parse(bare), kind))

    def has_twin(self, text: str, kind: str, bare: str | None = None) -> bool:
        """Whether wrong_twin(parse(text), kind) gives a query. bare: the text without its numbers, where the caller has it."""
        return self._twin(bare_numbers(text)[0] if bare is None else bare, kind) is not None

    def said(self, bare: str, family: int, kind: str | None = None) -> str:
        """question() of a text without its numbers."""
        return self._once((bare, kind, family), lambda: question((kind and self._twin(bare, kind)) or parse(bare), family))

    def full(self, bare: str, back: dict[str, str]) -> str:
        """full_numbers() of a text that comes again and again, which is cut at its names once."""
        parts = self._once(("cut", bare), lambda: NUMBERED.split(bare))
        return "".join([back.get(x, x) if k % 2 else x for k, x in enumerate(parts)]) if len(parts) > 1 else bare

    def question(self, text: str, family: int, kind: str | None = None) -> str:
        """question() of a query's text, or of its twin of a kind where it has one."""
        bare, back = bare_numbers(text)
        return full_numbers(self.said(bare, family, kind), back)


def spoil_grammar(text: str) -> str:
    return re.sub(r"\b(is|are|the) ", "", text).lower().replace("?", "")
