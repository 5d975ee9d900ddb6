"""Chat formatting: a hidden Markov model over speaker markers and line features recovers roles by Viterbi.

A transcript keeps one marker style. States are (style, role, first or later line of a turn), and only states of one
style follow one another; roles are system, user, assistant, and any other, whose name its marker tells. A line is
observed as the speaker marker that opens it, seen from each style (none, one of this style by role, one of another
style), whether the line before it was blank, its length class and whether it ends as a question. So a line that
looks like a marker of another style than the transcript's is text. The tables are counts over labelled transcripts,
at most ``max_convs`` (the documented bound of the sample), with add-one smoothing and ``PRIOR`` more counts of each
role's own marker. The most likely path gives the turns; a line in a first-line state opens a turn, its marker is
taken off, and the turns are written in one canonical form.

``parse`` takes transcripts ``conv_id, part, context, transcript``; :func:`transcripts` writes such raw texts from a
table of turns in several marker styles. A conversation is cut after every ``part_turns`` turn numbers, so none,
however long, is gathered whole; a part after the first is read with the last turn before it as context, so the chain
goes on, and the context's lines give no turns. Rows that share a turn number keep apart by text order; if one turn
number holds very many rows, they are dealt over parts of their own by a hash of the text.

Null transcripts and empty ones have no turns. Null and empty roles are the role ``unknown``; other spellings of the
three main roles are those roles. A null text is an empty turn. Rows with null conversation ids are left out.
"""

from __future__ import annotations

import re

import numpy as np
import pandas as pd
from pyspark.sql import Column, DataFrame, Window
from pyspark.sql import functions as F

from featgreedy.llm.common import ship

ROLES = ("system", "user", "assistant", "other")
#: Spellings of speaker names that markers use.
NAMES = {"system": ("system", "instructions"), "user": ("user", "human", "q"), "assistant": ("assistant", "ai", "bot", "a")}
_ROLE_OF = {n: r for r, names in NAMES.items() for n in names}
STYLES = ("colon", "heading", "tag", "bracket", "bold", "letter")
#: Counts of a role's own marker in the style, before any labelled line.
PRIOR = 4
#: Names of roles beside the main three that a model may know.
MAX_NAMES = 10_000
NONE, FOREIGN = 0, 1 + len(ROLES)


def marker_pattern(names=()) -> re.Pattern:
    """Markers of the known spellings and of other role ``names``; the named group tells the form."""
    known = "|".join(re.escape(n) for n in sorted({*_ROLE_OF, *names}, key=lambda n: (-len(n), n)))
    # a form's group is followed by that of its name
    forms = (("tag", r"<\|({0})\|>"), ("heading", r"#{{1,4}} ?({0}):?$"), ("bracket", r"\[({0})\]:?"), ("bold", r"\*\*({0}):?\*\*:?"), ("colon", r"({0}) ?[:>]"))
    return re.compile("^(?:" + "|".join(f"(?P<{form}>" + p.format(known) + ")" for form, p in forms) + r")\s*", re.IGNORECASE)


def marker(line: str, pattern: re.Pattern) -> tuple[str | None, str | None, int]:
    """Form and speaker's name of the marker that opens a line, and the length of its text."""
    m = pattern.match(line)
    if not m:
        return None, None, 0
    form = m.lastgroup
    name = m.group(pattern.groupindex[form] + 1).lower()
    return form, name, m.end()


def role_of(name: str) -> int:
    return ROLES.index(_ROLE_OF.get(name, "other"))


def seen_from(form: str | None, name: str | None) -> np.ndarray:
    """The marker as each style sees it."""
    out = np.full(len(STYLES), NONE if form is None else FOREIGN)
    if form is None:
        return out
    kind = 1 + role_of(name)
    if form != "colon":
        out[STYLES.index(form)] = kind
    elif name in ("q", "a"):
        out[STYLES.index("letter")] = kind
    else:
        out[STYLES.index("colon")] = kind
        if _ROLE_OF.get(name) not in ("user", "assistant"):
            out[STYLES.index("letter")] = kind
    return out


def observe(lines: list[str], pattern: re.Pattern) -> tuple[np.ndarray, np.ndarray, list]:
    """Per line: the marker from each style; blank before, length class, question; the marker itself."""
    marks = [marker(x, pattern) for x in lines]
    kinds = np.array([seen_from(f, n) for f, n, _ in marks]).reshape(len(lines), len(STYLES))
    rest = np.zeros((len(lines), 3), np.int64)
    blank = True
    for i, x in enumerate(lines):
        n = len(x.strip())
        rest[i] = blank, 0 if not n else 1 if n < 80 else 2 if n < 400 else 3, x.rstrip().endswith("?")
        blank = not n
    return kinds, rest, marks


SIZES = (2 + len(ROLES), 2, 4, 2)
STATES = 2 * len(ROLES)


class Model:
    """Counts of starts, moves and features, shared by the styles, and the names of other roles."""

    def __init__(self, names=()):
        self.names = tuple(sorted(names))
        self.start = np.ones(STATES)
        self.move = np.ones((STATES, STATES))
        self.see = [np.ones((STATES, n)) for n in SIZES]
        for r in range(len(ROLES)):
            self.see[0][2 * r, 1 + r] += PRIOR
            self.see[0][2 * r + 1, NONE] += PRIOR

    def add(self, states: np.ndarray, seen: np.ndarray) -> None:
        """``seen``: per line the marker from the transcript's own style, then the other features."""
        if len(states):
            self.start[states[0]] += 1
            np.add.at(self.move, (states[:-1], states[1:]), 1)
            for f, table in enumerate(self.see):
                np.add.at(table, (states, seen[:, f]), 1)

    def tables(self):
        log = lambda t: np.log(t / t.sum(-1, keepdims=True))
        move = self.move.copy()
        for r in range(len(ROLES)):
            for q in range(len(ROLES)):
                if q != r:  # a later line follows lines of its own role only
                    move[2 * r, 2 * q + 1] = move[2 * r + 1, 2 * q + 1] = 1e-12
        start = self.start.copy()
        start[1::2] = 1e-12
        return log(start), log(move), [log(t) for t in self.see], self.names


def viterbi(tables, kinds: np.ndarray, rest: np.ndarray) -> np.ndarray:
    """Most likely states of the best style; ties go to the smaller style and state."""
    start, move, see = tables[:3]
    plain = sum(t[:, rest[:, f]].T for f, t in enumerate(see[1:]))
    emit = see[0].T[kinds] + plain[:, None, :]  # line, style, state
    n, styles = kinds.shape
    back = np.zeros((n, styles, STATES), np.int64)
    best = start + emit[0]
    for i in range(1, n):
        both = best[:, :, None] + move
        back[i] = both.argmax(1)
        best = both.max(1) + emit[i]
    s = int(best.max(1).argmax())
    path = np.zeros(n, np.int64)
    path[-1] = best[s].argmax()
    for i in range(n - 1, 0, -1):
        path[i - 1] = back[i, s, path[i]]
    return path


def turns(tables, transcript: str | None, pattern: re.Pattern | None = None, context: str | None = None) -> list[tuple[str, str]]:
    """Roles and texts of the transcript's turns; ``context``: lines before it, whose turns are left out."""
    lines = (transcript or "").split("\n")
    if lines == [""]:
        return []
    before = context.split("\n") if context else []
    pattern = pattern or marker_pattern(tables[3])
    kinds, rest, marks = observe(before + lines, pattern)
    path = viterbi(tables, kinds, rest)[len(before) :]
    out: list[tuple[str, list[str]]] = []
    for i, (s, x) in enumerate(zip(path, lines, strict=True)):
        form, name, cut = marks[len(before) + i]
        if s % 2 == 0 or not out:
            role = ROLES[s // 2]
            out.append((name if role == "other" and name else role, [x[cut:]] if x[cut:] or form is None else []))
        else:
            out[-1][1].append(x)
    return [(r, "\n".join(t).strip()) for r, t in out]


def render(found: list[tuple[str, str]]) -> str:
    """The canonical form."""
    return "".join(f"<|{r}|>\n{t}\n<|end|>\n" for r, t in found)


def role_name(column: str = "role") -> Column:
    """One spelling of a role."""
    plain = F.coalesce(F.nullif(F.lower(F.trim(F.col(column))), F.lit("")), F.lit("unknown"))
    out = plain
    for role, names in NAMES.items():
        out = F.when(plain.isin(*names), role).otherwise(out)
    return out


def transcripts(conversations: DataFrame, part_turns: int = 256, most: int = 100_000) -> DataFrame:
    """``conv_id, part, context, transcript, roles, texts`` in marker styles dealt by the conversation's hash.

    ``part`` grows with the turns. Turn numbers of more than ``most`` rows are spread over parts by their texts.
    """
    style = F.pmod(F.xxhash64("conv_id"), F.lit(5))
    rows = conversations.filter("conv_id IS NOT NULL").select("conv_id", F.coalesce("turn", F.lit(0)).cast("long").alias("turn"), role_name().alias("role"), F.coalesce("text", F.lit("")).alias("text"))
    name, text = F.initcap("role"), F.col("text")
    human = F.create_map(*[F.lit(x) for p in (("system", "Instructions"), ("user", "Human"), ("assistant", "AI")) for x in p])
    letter = F.create_map(*[F.lit(x) for p in (("user", "Q"), ("assistant", "A")) for x in p])
    pick = lambda table: F.coalesce(F.try_element_at(table, F.col("role")), name)
    line = (
        F.when(style == 0, F.concat(name, F.lit(": "), text))
        .when(style == 1, F.concat(F.lit("### "), pick(human), F.lit("\n"), text))
        .when(style == 2, F.concat(F.lit("<|"), F.col("role"), F.lit("|>\n"), text))
        .when(style == 3, F.concat(F.lit("["), name, F.lit("] "), text))
        .otherwise(F.concat(pick(letter), F.lit(": "), text))
    )
    step = F.floor(F.col("turn") / part_turns)
    crowd = rows.groupBy("conv_id", step.alias("step")).agg(F.count("*").alias("n")).filter(F.col("n") > most)
    crowd = crowd.select("conv_id", "step", F.ceil(F.col("n") / most * 4).alias("cuts"))
    rows = rows.withColumn("step", step).join(crowd, ["conv_id", "step"], "left")
    sub = F.coalesce(F.pmod(F.xxhash64("turn", "text"), F.col("cuts")), F.lit(0))
    rows = rows.select("conv_id", "step", sub.alias("sub"), F.struct("turn", "text", "role", line.alias("line")).alias("x"))
    g = rows.groupBy("conv_id", "step", "sub").agg(F.sort_array(F.collect_list("x")).alias("xs"))
    g = g.select("conv_id", "step", "sub", F.array_join(F.col("xs.line"), "\n").alias("transcript"), F.col("xs.role").alias("roles"), F.col("xs.text").alias("texts"))
    # the last turn of the part before; only conversations of several parts have one
    late = rows.filter("step > 0").select("conv_id", "step").distinct()
    last = rows.withColumn("step", F.col("step") + 1).join(late, ["conv_id", "step"], "left_semi").groupBy("conv_id", "step").agg(F.max("x").alias("x"))
    g = g.join(last.select("conv_id", "step", F.col("x.line").alias("context")), ["conv_id", "step"], "left")
    return g.select("conv_id", F.struct("step", "sub").alias("part"), "context", "transcript", "roles", "texts")


def own_style(conv_id, row_roles, kinds: np.ndarray, firsts: list[int]) -> int:
    """The style in which most opening lines carry the marker of their role."""
    want = np.array([1 + (ROLES.index(r) if r in ROLES else len(ROLES) - 1) for r in row_roles])
    return int((kinds[firsts] == want[:, None]).sum(0).argmax()) if firsts else 0


def fit(rows, names=()) -> tuple:
    """Tables from rows of :func:`transcripts`."""
    model = Model(names)
    pattern = marker_pattern(model.names)
    for row in rows:
        lines = row["transcript"].split("\n")
        kinds, rest, marks = observe(lines, pattern)
        states, firsts, at = np.zeros(len(lines), np.int64), [], 0
        for role, text in zip(row["roles"], row["texts"], strict=True):
            if at >= len(lines):
                break
            r = ROLES.index(role) if role in ROLES else len(ROLES) - 1
            alone = marks[at][0] in ("heading", "tag") and marks[at][2] == len(lines[at])
            n = text.count("\n") + 1 + alone
            firsts.append(at)
            states[at : at + n] = 2 * r + 1
            states[at] = 2 * r
            at += n
        s = own_style(row["conv_id"], row["roles"][: len(firsts)], kinds, firsts)
        model.add(states, np.column_stack([kinds[:, s], rest]))
    return model.tables()


def _parse(tables):
    def run(batches):
        held = tables.value
        pattern = marker_pattern(held[3])
        for pdf in batches:
            got = [turns(held, t, pattern, c) for t, c in zip(pdf["transcript"], pdf["context"], strict=True)]
            yield pd.DataFrame({"conv_id": pdf["conv_id"], "step": pdf["step"], "sub": pdf["sub"], "roles": [[r for r, _ in g] for g in got], "texts": [[t for _, t in g] for g in got], "rendered": [render(g) for g in got]})

    return run


def parse(raw: DataFrame, tables) -> DataFrame:
    """``conv_id, part, context, transcript`` -> ``conv_id, part, roles, texts, rendered``."""
    shared = raw.sparkSession.sparkContext.broadcast(tables)
    flat = raw.select("conv_id", F.col("part.step").alias("step"), F.col("part.sub").alias("sub"), "context", "transcript")
    got = flat.mapInPandas(_parse(shared), "conv_id long, step long, sub long, roles array<string>, texts array<string>, rendered string")
    return got.select("conv_id", F.struct("step", "sub").alias("part"), "roles", "texts", "rendered")


def role_names(conversations: DataFrame) -> list[str]:
    """Names of the roles beside the main three, of all rows."""
    found = conversations.select(role_name().alias("r")).filter(~F.col("r").isin(*NAMES)).distinct().limit(MAX_NAMES + 1).collect()
    if len(found) > MAX_NAMES:
        raise ValueError(f"more than {MAX_NAMES} different roles")
    return sorted(r["r"] for r in found)


def sample(conversations: DataFrame, max_convs: int = 1000):
    """Labelled transcripts of at most ``max_convs`` conversations, in the order of a hash of their ids."""
    ids = conversations.filter("conv_id IS NOT NULL").select("conv_id").distinct().orderBy(F.xxhash64("conv_id"), "conv_id").limit(max_convs)
    return transcripts(conversations.join(F.broadcast(ids), "conv_id", "left_semi")).toLocalIterator()


def contract(conversations: DataFrame) -> DataFrame:
    """Every conversation written raw, parsed back and rendered: one row per turn, numbered within its conversation."""
    raw = transcripts(conversations)
    got = parse(raw, fit(sample(conversations), role_names(conversations))).withColumn("n", F.size("roles"))
    before = Window.partitionBy("conv_id").orderBy("part").rowsBetween(Window.unboundedPreceding, -1)
    got = got.withColumn("base", F.coalesce(F.sum("n").over(before), F.lit(0)))
    each = got.select("conv_id", "base", F.posexplode(F.arrays_zip("roles", "texts")).alias("i", "x"))
    return each.select("conv_id", (F.col("base") + F.col("i")).alias("turn"), F.col("x.roles").alias("role"), F.sha2("x.texts", 256).alias("text_sha256"))


#: The turns of the table itself: what parsing must recover.
ORACLE = r"""
WITH r AS (SELECT conv_id, coalesce(turn, 0) AS t, coalesce(text, '') AS x, coalesce(nullif(lower(trim(role)), ''), 'unknown') AS r FROM conversations WHERE conv_id IS NOT NULL),
c AS (SELECT conv_id, t, x, CASE WHEN r IN ('system', 'instructions') THEN 'system' WHEN r IN ('user', 'human', 'q') THEN 'user' WHEN r IN ('assistant', 'ai', 'bot', 'a') THEN 'assistant' ELSE r END AS role FROM r)
SELECT conv_id, row_number() OVER (PARTITION BY conv_id ORDER BY t, x, role) - 1 AS turn, role, sha256(trim(x, chr(32) || chr(9) || chr(10) || chr(13))) AS text_sha256 FROM c
"""

ship(__name__)
