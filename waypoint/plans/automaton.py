"""Regular expressions over edge labels and small automata without empty moves (driver side).

Syntax: labels, ``/`` concatenation, ``|``, ``* + ?``, ``{m,n}``, parentheses, ``()`` for the empty word, ``.`` any label,
``!(a|b)`` any other label, ``^a`` an edge walked backwards.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

_LEX = re.compile(r"\s*(?:(\^?[A-Za-z_][\w:-]*)|(\{\d+(?:,\d*)?\})|(.))")


@dataclass(frozen=True)
class Automaton:
    """States are 0..n-1 with 0 initial; ``moves`` are (state, label, next) without empty moves."""

    n: int
    moves: frozenset
    finals: frozenset

    @property
    def labels(self) -> set[str]:
        return {a for _, a, _ in self.moves}

    def accepts(self, word) -> bool:
        here = {0}
        for a in word:
            here = {t for s, b, t in self.moves if s in here and b == a}
        return bool(here & self.finals)

    def is_deterministic(self) -> bool:
        return len({(s, a) for s, a, _ in self.moves}) == len(self.moves)

    def is_unambiguous(self) -> bool:
        """No two different runs of one word: in the trimmed self-product no pair of different states is useful."""
        t = trimmed(self)
        step: dict = {}
        back: dict = {}
        for s, a, x in t.moves:
            for r, b, y in t.moves:
                if a == b:
                    step.setdefault((s, r), set()).add((x, y))
                    back.setdefault((x, y), set()).add((s, r))
        ahead = _closure({(0, 0)}, step)
        behind = _closure({(f, g) for f in t.finals for g in t.finals}, back)
        return all(p == q for p, q in ahead & behind)


def _closure(start: set, step: dict) -> set:
    seen, todo = set(start), list(start)
    while todo:
        for y in step.get(todo.pop(), ()):
            if y not in seen:
                seen.add(y)
                todo.append(y)
    return seen


def parse(text: str):
    """A nested tuple: ("label", a), ("any",), ("not", labels), ("empty",), ("cat"|"or", x, y), ("star", x)."""
    tokens = [next(t for t in m if t) for m in _LEX.findall(text.strip())]
    at = 0

    def peek():
        return tokens[at] if at < len(tokens) else None

    def take(want=None):
        nonlocal at
        t = peek()
        if t is None or (want and t != want):
            raise ValueError(f"{want or 'more'} expected in {text!r}")
        at += 1
        return t

    def either():
        x = chain()
        while peek() == "|":
            take()
            x = ("or", x, chain())
        return x

    def chain():
        x = repeated()
        while peek() == "/":
            take()
            x = ("cat", x, repeated())
        return x

    def repeated():
        x = atom()
        while peek() and (peek() in "*+?" or peek()[0] == "{"):
            t = take()
            if t == "*":
                x = ("star", x)
            elif t == "+":
                x = ("cat", x, ("star", x))
            elif t == "?":
                x = ("or", x, ("empty",))
            else:
                low, _, high = t[1:-1].partition(",")
                y = ("empty",)
                for _ in range(int(low)):
                    y = ("cat", y, x)
                if "," in t and not high:
                    y = ("cat", y, ("star", x))
                for _ in range(int(high or low) - int(low)):
                    y = ("cat", y, ("or", x, ("empty",)))
                x = y
        return x

    def atom():
        t = take()
        if t == "(":
            if peek() == ")":
                take()
                return ("empty",)
            x = either()
            take(")")
            return x
        if t == ".":
            return ("any",)
        if t == "!":
            names = set()

            def gather(x):
                if x[0] == "label":
                    names.add(x[1])
                elif x[0] == "or":
                    gather(x[1])
                    gather(x[2])
                else:
                    raise ValueError("only labels may be negated")

            gather(atom())
            return ("not", frozenset(names))
        if re.fullmatch(r"\^?[A-Za-z_][\w:-]*", t):
            return ("label", t)
        raise ValueError(f"{t!r} not expected in {text!r}")

    tree = either()
    if peek():
        raise ValueError(f"{peek()!r} left over in {text!r}")
    return tree


def position_automaton(tree, alphabet=()) -> Automaton:
    """One state for each label place of the expression, and an initial one."""
    places: list[frozenset] = [frozenset()]
    follow: set[tuple[int, int]] = set()

    def leaf(labels):
        places.append(frozenset(labels))
        p = len(places) - 1
        return False, {p}, {p}

    def walk(x):
        kind = x[0]
        if kind == "label":
            return leaf([x[1]])
        if kind == "any":
            return leaf(alphabet)
        if kind == "not":
            return leaf(set(alphabet) - x[1])
        if kind == "empty":
            return True, set(), set()
        if kind == "star":
            _, first, last = walk(x[1])
            follow.update((p, q) for p in last for q in first)
            return True, first, last
        e1, f1, l1 = walk(x[1])
        e2, f2, l2 = walk(x[2])
        if kind == "or":
            return e1 or e2, f1 | f2, l1 | l2
        follow.update((p, q) for p in l1 for q in f2)
        return e1 and e2, f1 | (f2 if e1 else set()), l2 | (l1 if e2 else set())

    empty, first, last = walk(tree)
    follow.update((0, p) for p in first)
    moves = frozenset((p, a, q) for p, q in follow for a in places[q])
    return Automaton(len(places), moves, frozenset(last | ({0} if empty else set())))


def thompson_automaton(tree, alphabet=()) -> Automaton:
    """The construction with empty moves, which are then closed away."""
    n, moves, empties = 0, [], []

    def state() -> int:
        nonlocal n
        n += 1
        return n - 1

    def walk(x) -> tuple[int, int]:
        if x[0] == "cat":
            a, b = walk(x[1])
            c, d = walk(x[2])
            empties.append((b, c))
            return a, d
        s, t = state(), state()
        if x[0] == "empty":
            empties.append((s, t))
        elif x[0] == "star":
            a, b = walk(x[1])
            empties.extend([(s, a), (b, t), (s, t), (b, a)])
        elif x[0] == "or":
            for y in x[1:]:
                a, b = walk(y)
                empties.extend([(s, a), (b, t)])
        else:
            labels = [x[1]] if x[0] == "label" else set(alphabet) - (x[1] if x[0] == "not" else set())
            moves.extend((s, a, t) for a in labels)
        return s, t

    start, end = walk(tree)
    step: dict = {}
    for a, b in empties:
        step.setdefault(a, set()).add(b)
    reach = {s: _closure({s}, step) for s in range(n)}
    number = {start: 0} | {s: i + 1 for i, s in enumerate(x for x in range(n) if x != start)}
    out = {(number[s], a, number[t]) for s in range(n) for p, a, t in moves if p in reach[s]}
    return trimmed(Automaton(n, frozenset(out), frozenset(number[s] for s in range(n) if end in reach[s])))


def trimmed(a: Automaton) -> Automaton:
    """Only states on some accepting run (and the initial one)."""
    ahead: dict = {}
    behind: dict = {}
    for s, _, t in a.moves:
        ahead.setdefault(s, set()).add(t)
        behind.setdefault(t, set()).add(s)
    useful = (_closure({0}, ahead) & _closure(set(a.finals), behind)) | {0}
    number = {s: i for i, s in enumerate(sorted(useful))}
    return Automaton(len(useful), frozenset((number[s], x, number[t]) for s, x, t in a.moves if s in useful and t in useful), frozenset(number[f] for f in a.finals if f in useful))


def determinised(a: Automaton, most: int = 4096) -> Automaton:
    """The subset construction, trimmed; more than ``most`` states raise."""
    number = {frozenset([0]): 0}
    todo, moves = [frozenset([0])], set()
    while todo:
        here = todo.pop()
        out: dict = {}
        for s, x, t in a.moves:
            if s in here:
                out.setdefault(x, set()).add(t)
        for x, there in out.items():
            there = frozenset(there)
            if there not in number:
                if len(number) >= most:
                    raise ValueError("the deterministic automaton grows too large")
                number[there] = len(number)
                todo.append(there)
            moves.add((number[here], x, number[there]))
    return trimmed(Automaton(len(number), frozenset(moves), frozenset(i for s, i in number.items() if s & a.finals)))


def minimised(a: Automaton) -> Automaton:
    """The least deterministic automaton of the language, by refining classes of states."""
    a = determinised(a)
    sink = a.n
    step = {(s, x): t for s, x, t in a.moves}
    labels = sorted(a.labels)
    group = {s: int(s in a.finals) for s in range(a.n + 1)}
    while True:
        key = {s: (group[s], tuple(group[step.get((s, x), sink)] for x in labels)) for s in group}
        names = {k: i for i, k in enumerate(sorted(set(key.values())))}
        new = {s: names[key[s]] for s in group}
        if len(set(new.values())) == len(set(group.values())):
            break
        group = new
    order = sorted(range(a.n), key=lambda s: s)
    number: dict = {}
    for s in order:
        number.setdefault(group[s], len(number))
    return trimmed(Automaton(len(number), frozenset((number[group[s]], x, number[group[t]]) for s, x, t in a.moves), frozenset(number[group[f]] for f in a.finals)))


def single_final(a: Automaton) -> tuple[Automaton, bool]:
    """One fresh final state that copies the moves into the old finals; and whether the empty word was accepted, which is peeled off."""
    fresh = a.n
    moves = set(a.moves) | {(s, x, fresh) for s, x, t in a.moves if t in a.finals}
    return trimmed(Automaton(a.n + 1, frozenset(moves), frozenset([fresh]))), 0 in a.finals


def reversed_automaton(a: Automaton) -> Automaton:
    """The language read backwards, with labels turned around (a and ^a change places)."""
    one, empty = single_final(a)
    final = next(iter(one.finals), None)
    if final is None:
        return Automaton(1, frozenset(), frozenset([0] if empty else []))
    swap = {final: 0, 0: final}
    name = lambda s: swap.get(s, s)
    moves = frozenset((name(t), x[1:] if x[0] == "^" else "^" + x, name(s)) for s, x, t in one.moves)
    return trimmed(Automaton(one.n, moves, frozenset([final] + ([0] if empty else []))))


def prepared(regex: str, alphabet=(), ambiguity: str = "determinise", construction: str = "position") -> Automaton:
    """The automaton of a query under an ambiguity policy: ``determinise``, ``error`` or ``allow``."""
    tree = parse(regex)
    a = trimmed((position_automaton if construction == "position" else thompson_automaton)(tree, alphabet))
    if ambiguity == "determinise":
        return minimised(a)
    if ambiguity == "error" and not a.is_unambiguous():
        raise ValueError("the automaton is ambiguous")
    return a


def measured(regex: str, alphabet=()) -> list[tuple[str, int, int, bool, bool]]:
    """Construction, states, moves, deterministic and unambiguous of an expression's automata, to see what determinising costs."""
    tree = parse(regex)
    position = trimmed(position_automaton(tree, alphabet))
    built = {"position": position, "thompson": thompson_automaton(tree, alphabet), "deterministic": determinised(position), "minimal": minimised(position), "single_final": single_final(minimised(position))[0]}
    return [(k, a.n, len(a.moves), a.is_deterministic(), a.is_unambiguous()) for k, a in built.items()]
