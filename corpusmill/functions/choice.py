"""Multiple-choice questions in plain text: option runs, components, standard form."""

from __future__ import annotations

import re
from dataclasses import dataclass

# The words that begin an answer.
ANSWERS = ("answer:", "solution:", "reply:", "response:", "ans:", "a:", "r:")
_ROMAN = ((1000, "m"), (900, "cm"), (500, "d"), (400, "cd"), (100, "c"), (90, "xc"), (50, "l"), (40, "xl"), (10, "x"), (9, "ix"), (5, "v"), (4, "iv"), (1, "i"))
_SERIAL = re.compile(r"\s*([A-Za-z]|[0-9]{1,18}|[ivxlcdmIVXLCDM]+)\s?([.\-)>\] ])\s*(.*)$", re.S)


def roman(mark: str) -> int | None:
    """Value of a lower-case numeral in its standard form."""
    value, rest = 0, mark
    for n, sign in _ROMAN:
        while rest.startswith(sign):
            value, rest = value + n, rest[len(sign) :]
    return value if not rest and "".join(_written(value)) == mark else None


def _written(value: int):
    for n, sign in _ROMAN:
        yield sign * (value // n)
        value %= n


@dataclass(frozen=True)
class Question:
    stem: str
    options: tuple[str, ...]
    answer: str
    explanation: str | None
    first: int
    style: str


def serials(line: str) -> list[tuple[str, int, str, str]]:
    """All readings of a line as an option: ``(style, ordinal, delimiter, rest)``."""
    m = _SERIAL.match(line)
    if not m or not m[3].strip():
        return []
    mark, delimiter, rest = m[1].lower(), m[2], m[3].strip()
    out = []
    if len(mark) == 1 and mark.isalpha():
        out.append(("letter", ord(mark) - 96, delimiter, rest))
    if mark.isalpha() and (value := roman(mark)):
        out.append(("roman", value, delimiter, rest))
    if mark.isdigit():
        out.append(("arabic", int(mark), delimiter, rest))
    return out


def choice_runs(lines: list[str]) -> list[tuple[int, int, str, tuple[str, ...]]]:
    """Longest runs ``(start, end, style, options)`` that count up from the first serial; two options or more."""
    parsed = [serials(x) for x in lines]
    out, at = [], 0
    while at < len(lines):
        best = None
        for style, ordinal, delimiter, rest in parsed[at]:
            if ordinal != 1:
                continue
            options, k = [rest], at + 1
            while k < len(lines):
                follow = next((r for s, o, d, r in parsed[k] if (s, o, d) == (style, len(options) + 1, delimiter)), None)
                if follow is None:
                    break
                options.append(follow)
                k += 1
            if len(options) >= 2 and (best is None or len(options) > len(best[3])):
                best = (at, k, style, tuple(options))
        if best:
            out.append(best)
            at = best[1]
        else:
            at += 1
    return out


def is_answer(line: str) -> bool:
    return line.strip().lower().startswith(ANSWERS)


def choice_questions(text: str | None, answer_position: str = "after") -> list[Question]:
    """Questions with stem, options and answer; the answer stands after the options, before the stem, or either with ``any``."""
    lines = [x for x in (text or "").split("\n") if x.strip()]
    out = []
    for start, end, style, options in choice_runs(lines):
        if start == 0:
            continue
        answer = explanation = None
        if answer_position in ("after", "any") and end < len(lines) and is_answer(lines[end]):
            answer = lines[end]
            if end + 1 < len(lines) and lines[end + 1].strip().lower().startswith("explanation:"):
                explanation = lines[end + 1]
        elif answer_position in ("before", "any") and start >= 2 and is_answer(lines[start - 2]):
            answer = lines[start - 2]
        if answer:
            out.append(Question(lines[start - 1].strip(), options, answer.strip(), explanation and explanation.strip(), start, style))
    return out


def after_colon(line: str) -> str:
    return line.partition(":")[2].strip()


def _letters(k: int) -> str:
    """A to Z, then AA, AB and so on."""
    return (_letters(k // 26 - 1) if k >= 26 else "") + chr(65 + k % 26)


def format_question(q: Question) -> str:
    """Stem without serial, options as A. B. C., prefixed answer and explanation, in this order."""
    stem = re.sub(r"^\s*([0-9]{1,3}|[A-Za-z]|[ivxIVX]{1,4})[.)>\]]\s*", "", q.stem)
    parts = [stem, *[f"{_letters(i)}. {o}" for i, o in enumerate(q.options)], f"Answer: {after_colon(q.answer)}"]
    return "\n".join(parts + ([f"Explanation: {after_colon(q.explanation)}"] if q.explanation else []))
