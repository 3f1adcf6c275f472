"""The experiments' dictionaries. Pattern ids count from 1 in the order given."""

from __future__ import annotations

from runloom.types import Run


def _runs(text: str) -> tuple:
    """"F2 O3" as runs; a symbol without a number is one long."""
    out = []
    for part in text.split():
        sym = part.rstrip("0123456789")
        out.append(Run(sym, int(part[len(sym) :] or 1)))
    return tuple(out)


def _numbered(patterns: list) -> list[tuple[int, object]]:
    return [(k + 1, p) for k, p in enumerate(patterns)]


#: The worked example's text and patterns.
EXAMPLE = "aaaabbbaaaccbaa"
SIX = _numbered([_runs(x) for x in ("a5 b1", "a5 b3 a2", "a5 b3 a1", "a3 b3 a1", "b2 a1", "b2")])
EVENTS = _numbered([_runs(x) for x in ("view click purchase", "error2", "click error view", "error signup2", "view2 click", "purchase3", "click view click", "signup error2 purchase")])
LINE_STATUS = _numbered([_runs(x) for x in ("F2 O3", "O F O F", "F4", "O5 F2", "F O6", "F3 O F2 O", "O8")])
QUANTITY = _numbered([_runs(x) for x in ("L10 H", "H2", "H L5 H", "L40", "H L3 H2", "L20 H L10")])
ORDER_STATUS = _numbered([_runs(x) for x in ("F2 O", "O P", "P3", "O F P", "F O F O", "P F2")])
QUALITY = _numbered(["110", "01", "1111", "0110", "111110", "101"])
SIGNS = _numbered(["++--", "+-+-", "+++++", "--+", "-+++-", "+------"])
ZEROS = _numbered(["#0000", "00", "r#000000", "0001", "1000", "99", "#00000000", "0000000"])
MORPHEMES = _numbered(["ll", "llll", "tion", "thth", "rre", "eea", "nnd", "ssh", "ere", "the"])
MARKUP = _numbered(["%%%", "***", "</p>", "<li>", "&amp;"])
TOKENS = _numbered([("of", "the"), ("in", "the"), ("to", "the"), ("of", "the", "and"), ("the", "the"), ("de", "la"), ("in", "der"), ("is", "that", "the")])
ROLES = _numbered([("user", "assistant", "user"), ("system", "user")])


def family(m: int) -> list[tuple[int, tuple]]:
    """The two-pattern family on one symbol."""
    return [(1, (Run("a", 1),)), (2, (Run("a", m - 1),))]


def adversary(q: int) -> list[tuple[int, tuple]]:
    """a^i b for i up to q: links that drop one symbol at a time are followed for each symbol."""
    return [(i, (Run("a", i), Run("b", 1))) for i in range(1, q + 1)]
