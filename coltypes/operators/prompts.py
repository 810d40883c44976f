"""Prompts in this engine's own words: discovery for a cluster, checks of a closed list, whole-table baselines."""

from __future__ import annotations

import json
from itertools import zip_longest

DISCOVER = """These table columns were grouped because their headers and their contents look alike.
Say which kinds of things their values stand for.
Headers: {headers}
Some of the values: {sample}
Headers found next to them (tables with it / tables): {context}
Types in use so far: {candidates}
How to decide:
1. A type says what a value means, more closely than a data type would.
2. Weigh headers and values together, spell out short forms, and trust the values if the two disagree.
3. For each meaning, take a type in use only if it says exactly that; otherwise coin a new one.
4. A type that is merely near is wrong.
5. The neighbouring headers tell what the table is about.
6. No two types of the answer may mean the same.
Reply with JSON and nothing else: {{"answer": ["...", ...]}}"""

CHECK = """Column "{header}" of a table with these columns and some of its rows:
{context}
Some of its values: {sample}
Take the types of this list one at a time and test each: {candidates}
{rule}
If none of them truly holds, reply with an empty list.
Reply with JSON and nothing else: {{"answer": ["...", ...]}}"""

RULES = {
    "text": "A type passes if at least some of the values are such things; it need not cover all of them.",
    "num": "Numbers alone say little: a type passes if header and table make clear that this is what is counted or measured.",
}

JUDGE = """Column "{header}" of a table with these columns and some of its rows:
{context}
Some of its values: {sample}
Proposed type: {label}
Is it a true and telling type of at least some of these values? A word that fits any column, like value or name, is not.
Reply with JSON and nothing else: {{"answer": ["yes"]}} or {{"answer": ["no"]}}"""

WHOLE = """Name the semantic types of every column of this table, given its headers and some rows.
{rows}
{advice}{known}Reply with JSON and nothing else: {{"column": ["...", ...], ...}}"""

GUIDANCE = """A type says what a value means, more closely than a data type would. Weigh headers and values together,
spell out short forms, and trust the values if the two disagree. Give every meaning that a column holds, none twice.
"""
REUSE_RULES = "Use a known type only if it says exactly what the column holds, otherwise coin a new one.\n"


def discovery(request: dict) -> str:
    context = ", ".join(f"{h} ({n}/{of})" for h, n, of in request["context"])
    return DISCOVER.format(headers=", ".join(request["headers"]), sample=" | ".join(request["sample"]), context=context or "none", candidates=", ".join(request["candidates"]) or "none")


def closed_set(request: dict) -> str:
    return CHECK.format(header=request["header"], context=request["table"], sample=" | ".join(request["sample"]), candidates=", ".join(request["candidates"]), rule=RULES[request["kind"]])


def judgement(request: dict) -> str:
    return JUDGE.format(header=request["header"], context=request["table"], sample=" | ".join(request["sample"]), label=request["label"])


def whole_table(heads: list, guided: bool, known: list[str] | None) -> str:
    lines = [[h["header"] for h in heads], *zip_longest(*(h["values"] for h in heads), fillvalue="")]
    rows = "\n".join(" | ".join(line) for line in lines)
    listed = ("Types known so far: " + ", ".join(known) + "\n") if known is not None else ""
    return WHOLE.format(rows=rows, advice=GUIDANCE if guided else "", known=listed + (REUSE_RULES if guided and known is not None else ""))


def answer(labels: list[str]) -> str:
    return json.dumps({"answer": labels})
