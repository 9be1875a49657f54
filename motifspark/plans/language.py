"""Languages of process trees, bounded in the rounds of a loop."""

from __future__ import annotations

import hashlib

from .tree import Tree, canonical, nest

Word = tuple[str, ...]


class LanguageTooLarge(ValueError):
    pass


def interleave(u: Word, v: Word) -> set[Word]:
    """All merges of two words that keep the order within each."""
    rows: list[set[Word]] = [{v[:j]} for j in range(len(v) + 1)]
    for i, a in enumerate(u, 1):
        new = [{u[:i]}]
        for j, b in enumerate(v, 1):
            new.append({w + (b,) for w in new[j - 1]} | {w + (a,) for w in rows[j]})
        rows = new
    return rows[-1]


def words(t: Tree, rounds: int = 2, compact: bool = True, limit: int = 100_000) -> set[Word]:
    """Words with loop bodies run up to ``rounds`` times; ``compact`` loops run their body twice at least."""
    if t.is_leaf:
        return {(t.label,)}
    left, right = words(t.left, rounds, compact, limit), words(t.right, rounds, compact, limit)
    out: set[Word] = set()

    def add(more: set[Word]) -> None:
        out.update(more)
        if len(out) > limit:
            raise LanguageTooLarge(f"{t} has more than {limit} words")

    if t.op == "xor":
        add(left | right)
    elif t.op == "seq":
        for u in left:
            add({u + v for v in right})
    elif t.op == "and":
        for u in left:
            for v in right:
                add(interleave(u, v))
    else:
        now = left
        if not compact:
            add(now)
        for _ in range(rounds - 1):
            longer: set[Word] = set()
            for u in now:
                for v in right:
                    longer |= {u + v + w for w in left}
                    if len(longer) > limit:
                        raise LanguageTooLarge(f"{t} has more than {limit} words")
            now = longer
            add(now)
    return out


def shortest_words(t: Tree, limit: int = 100_000) -> set[Word]:
    """The words that decide containment: loops run exactly twice, as longer runs contain these."""
    return words(t, 2, True, limit)


def normal_form(t: Tree) -> Tree:
    """Flattened and re-nested form of associative operators, children of ``and``/``xor`` in order."""
    if t.is_leaf:
        return t
    if t.op == "loop":
        return Tree("loop", None, normal_form(t.left), normal_form(t.right))
    parts: list[Tree] = []

    def gather(x: Tree) -> None:
        if x.op == t.op:
            gather(x.left)
            gather(x.right)
        else:
            parts.append(normal_form(x))

    gather(t)
    return nest(t.op, parts if t.op == "seq" else sorted(parts, key=str))


def language_key(t: Tree, limit: int = 20_000) -> str:
    """Equal languages, equal keys: digest of the words of two and of three rounds, or of the normal form if the
    language is beyond the limit."""
    try:
        text = "\n".join("|".join(" ".join(w) for w in sorted(words(t, r, True, limit))) for r in (2, 3))
    except LanguageTooLarge:
        text = "form " + str(normal_form(canonical(t)))
    return hashlib.sha256(text.encode()).hexdigest()


def same_language(t: Tree, u: Tree, rounds: int = 3) -> bool:
    return words(t, rounds) == words(u, rounds)


def is_subsequence(word: Word, trace: list[str]) -> bool:
    it = iter(trace)
    return all(a in it for a in word)


def tail(trace: list[str], k: int) -> list[str]:
    """Events at places strictly after ``k`` (1-based); empty from the last place on."""
    return trace[k:]


def shadow_of_word(word: Word, trace: list[str]) -> list[int] | None:
    """Leftmost places (1-based) at which the word is found, or None."""
    out, at = [], 0
    for a in word:
        try:
            at = trace.index(a, at) + 1
        except ValueError:
            return None
        out.append(at)
    return out


def is_leftmost(word: Word, shadow: list[int], trace: list[str]) -> bool:
    """Whether each letter sits at its first place after its predecessor's."""
    return shadow == shadow_of_word(word, trace)
