"""Predictive clauses in SQL text.

    PREDICT(target [, predictor ...]) GIVEN relation

stands wherever a column may stand; ``relation`` is a view or a parenthesised query, and may also
follow a comparison (``PREDICT(t, x) = 'a' GIVEN r``).  The text is scanned past strings, quoted
names and comments; each clause is planned and becomes an alias of a derived table around the
FROM item, so the rest of the query is Spark's as usual and the optimiser sees plain expressions.
"""

from __future__ import annotations

import re
from dataclasses import dataclass

from pyspark.sql import DataFrame

from .session import ClauseError, Session

_TOKEN = re.compile(r"""(?s)--[^\n]*|/\*.*?\*/|'(?:[^'\\]|\\.|'')*'|"(?:[^"\\]|\\.)*"|`[^`]*`|[A-Za-z_]\w*|\s+|.""")


@dataclass(frozen=True)
class Clause:
    target: str
    predictors: tuple[str, ...]
    relation: str


@dataclass(frozen=True)
class _Word:
    text: str
    start: int
    stop: int

    def says(self, word: str) -> bool:
        return self.text.upper() == word


def _words(sql: str) -> list[_Word]:
    """Tokens without white space and comments."""
    out = [_Word(m.group(), m.start(), m.end()) for m in _TOKEN.finditer(sql)]
    return [w for w in out if not w.text.isspace() and not w.text.startswith("--") and not w.text.startswith("/*")]


def _close(words: list[_Word], at: int) -> int:
    """Index of the bracket that closes the one at ``at``."""
    depth = 0
    for i in range(at, len(words)):
        depth += (words[i].text == "(") - (words[i].text == ")")
        if not depth:
            return i
    raise ClauseError("a bracket is not closed")


def _relation(sql: str, words: list[_Word], at: int) -> tuple[str, int]:
    """Text of the relation that starts at word ``at`` and the index after it."""
    if at >= len(words):
        raise ClauseError("GIVEN without a relation")
    if words[at].text == "(":
        end = _close(words, at)
        return sql[words[at].start : words[end].stop], end + 1
    end = at + 1
    while end + 1 < len(words) and words[end].text == ".":
        end += 2
    return sql[words[at].start : words[end - 1].stop], end


def find_clauses(sql: str) -> tuple[str, dict[str, Clause]]:
    """The text with every clause replaced by an alias, and the clauses by alias.  Equal clauses
    share one alias."""
    words, out, at = _words(sql), [], 0
    found: dict[Clause, str] = {}
    i = 0
    while i < len(words):
        if not (words[i].says("PREDICT") and i + 1 < len(words) and words[i + 1].text == "("):
            i += 1
            continue
        end = _close(words, i + 1)
        inner = words[i + 2 : end]
        if any(w.says("PREDICT") for w in inner):
            raise ClauseError("a predicted attribute cannot be a predictor")
        names = [w.text.strip("`") for w in inner if w.text != ","]
        if not names or any(w.text == "," for w in inner[::2]):
            raise ClauseError("PREDICT needs a list of attributes")
        j, between = end + 1, ""
        if j < len(words) and not words[j].says("GIVEN"):
            # the relation may follow a comparison with a constant
            k = j
            while k < len(words) and k < j + 4 and not words[k].says("GIVEN"):
                k += 1
            if k >= len(words) or not words[k].says("GIVEN"):
                raise ClauseError("PREDICT without GIVEN")
            between = sql[words[end].stop : words[k].start]
            j = k
        elif j >= len(words):
            raise ClauseError("PREDICT without GIVEN")
        relation, after = _relation(sql, words, j + 1)
        clause = Clause(names[0], tuple(names[1:]), relation)
        alias = found.setdefault(clause, f"_predicted_{len(found)}")
        out += [sql[at : words[i].start], alias, between]
        at = words[after - 1].stop
        # SELECT PREDICT(t) ... without an alias keeps the attribute's name
        if not between and _in_select(words, i) and not _aliased(words, after):
            out.append(f" AS {clause.target}")
        i = after
    return "".join([*out, sql[at:]]), {a: c for c, a in found.items()}


def _in_select(words: list[_Word], at: int) -> bool:
    depth = 0
    for w in reversed(words[:at]):
        depth += (w.text == ")") - (w.text == "(")
        if depth < 0:
            return False
        if depth == 0 and w.text.upper() in ("FROM", "WHERE", "GROUP", "ORDER", "HAVING", "ON", "BY"):
            return False
        if depth == 0 and w.says("SELECT"):
            return words[at - 1].text == "," or words[at - 1].says("SELECT")
    return False


def _aliased(words: list[_Word], after: int) -> bool:
    return not (after >= len(words) or words[after].text == "," or words[after].says("FROM"))


def _from_item(sql: str) -> tuple[int, int]:
    """Span of the outermost FROM item (a name, with joins, or a parenthesised query)."""
    words, depth, start = _words(sql), 0, None
    for w in words:
        depth += (w.text == "(") - (w.text == ")")
        if depth == 0 and start is None and w.says("FROM"):
            start = w.stop
        elif start is not None and depth == 0 and w.text.upper() in ("WHERE", "GROUP", "ORDER", "HAVING", "LIMIT", "WINDOW", "UNION"):
            return start, w.start
    if start is None:
        raise ClauseError("no FROM item")
    return start, len(sql)


def predict_sql(session: Session, sql: str) -> DataFrame:
    """Run a query with predictive clauses."""
    plain, clauses = find_clauses(sql)
    spark = session.spark
    if not clauses:
        return spark.sql(sql)
    start, stop = _from_item(plain)
    item = plain[start:stop].strip()
    base = spark.sql(f"SELECT * FROM {item}")
    for alias, clause in clauses.items():
        given = spark.sql(clause.relation if clause.relation.startswith("(") else f"SELECT * FROM {clause.relation}")
        base = session.predict(base, clause.target, list(clause.predictors) or None, given, name=alias)
    view = f"_predictive_{abs(hash(sql)) % 10**9}_{session.planned}"
    base.createOrReplaceTempView(view)
    name = item.split()[-1] if re.fullmatch(r"[\w.]+(\s+(AS\s+)?\w+)?", item, re.I) else "predicted"
    return spark.sql(f"{plain[:start]} {view} AS {name.split('.')[-1]} {plain[stop:]}")
