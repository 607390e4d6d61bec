"""Quality rules as a short-circuit cascade.

Each rule rejects a text by one measure. A sample gives each rule's cost per
text, as characters, lines or numbers that it looks at, and the share of texts
it rejects; rules then run in the order of rejections per cost, and a text
leaves the cascade at its first rejection. The verdict is the same in any order;
only the work differs. Costs are counted, not timed, so the order, and with it
rejected_by, is the same on every machine.

Letters are the code points of Unicode's categories L, capitals those of Lu,
small letters those of Ll.

Defined results: null and empty texts have no words and fail the base rules;
an empty table gives no rows; repeated rows and null ids are judged each on
their own; without an id in the table the rules run in the order they are
declared; extra columns are ignored.
"""

from __future__ import annotations

from collections.abc import Callable, Iterator
from dataclasses import dataclass, field

import numpy as np
import pyarrow as pa
import regex
from pyspark.sql import DataFrame
from pyspark.sql import functions as F

from partnet.llm.common import map_rows, texts_as_bytes, tidy

SYMBOLS = b"#*$%&|<>"
#: from the first letter of a word to its end
lettered_words = regex.compile(r"\p{L}[^ ]*").findall
capitals, small_letters = regex.compile(r"\p{Lu}+").findall, regex.compile(r"\p{Ll}+").findall


@dataclass
class Measured:
    """A text with its words; derived lists are made when a rule first asks for them."""

    text: bytes
    words: list[bytes] = field(default_factory=list)
    n_symbols: int = 0
    n_dup_lines: int = 0
    n_repeat_words: int = 0
    word_chars: int = 0


def code_points(raw: bytes) -> int:
    return len(raw.decode("utf-8", "surrogatepass"))


def repeat_words(words: list[bytes]) -> int:
    """Words that lie in a 3-word window found at least twice, exactly: windows become pairs of dense numbers."""
    n = len(words)
    if n < 4:
        return 0
    codes: dict[bytes, int] = {}
    one = np.fromiter((codes.setdefault(x, len(codes)) for x in words), dtype=np.int64, count=n)
    if len(codes) == n:
        return 0
    _, pair = np.unique(one[:-1] * len(codes) + one[1:], return_inverse=True)
    _, window, count = np.unique(pair[:-1] * len(codes) + one[2:], return_inverse=True, return_counts=True)
    often = count[window] >= 2
    covered = np.zeros(n, dtype=bool)
    for shift in range(3):
        covered[shift : n - 2 + shift] |= often
    return int(covered.sum())


def duplicate_lines(text: bytes) -> int:
    seen, again = set(), 0
    for line in text.split(b"\n"):
        if line.strip():
            again += line in seen
            seen.add(line)
    return again


def measure(text: bytes) -> Measured:
    words = text.split()  # bytes.split() cuts at exactly the contract's white space
    return Measured(
        text, words,
        n_symbols=len(text) - len(text.translate(None, SYMBOLS)),
        n_dup_lines=duplicate_lines(text),
        n_repeat_words=repeat_words(words),
        word_chars=code_points(b"".join(words)),
    )


def fails_base(m: Measured) -> bool:
    n = len(m.words)
    return n < 50 or 100 * m.n_repeat_words > 50 * n


@dataclass(frozen=True)
class Rule:
    """work: how many characters, lines or numbers rejects() looks at."""

    name: str
    rejects: Callable[[Measured], bool]
    work: Callable[[Measured], int] = lambda m: 1


def many_symbols(m: Measured) -> bool:
    return 5 * m.n_symbols > len(m.words)


def many_repeated_lines(m: Measured) -> bool:
    lines = sum(1 for x in m.text.split(b"\n") if x.strip())
    return 10 * m.n_dup_lines > 3 * lines


def odd_word_length(m: Measured) -> bool:
    return not 2 * len(m.words) <= m.word_chars <= 15 * len(m.words)


def few_words_with_letters(m: Measured) -> bool:
    return 10 * len(lettered_words(b" ".join(m.words).decode("utf-8", "surrogatepass"))) < 7 * len(m.words)


def shouting(m: Measured) -> bool:
    text = m.text.decode("utf-8", "surrogatepass")
    return sum(map(len, capitals(text))) > sum(map(len, small_letters(text)))


RULES = (
    Rule("many_symbols", many_symbols),
    Rule("many_repeated_lines", many_repeated_lines, lambda m: 1 + m.text.count(b"\n")),
    Rule("odd_word_length", odd_word_length),
    Rule("few_words_with_letters", few_words_with_letters, lambda m: len(m.words) + m.word_chars),
    Rule("shouting", shouting, lambda m: 2 * len(m.text)),
)


def trials(texts: list[bytes], rules: tuple[Rule, ...] = RULES) -> list[tuple[str, int, int, int]]:
    """(rule, texts that pass the base rules, rejected, work) for each rule."""
    measured = [x for x in map(measure, texts) if not fails_base(x)]
    return [(r.name, len(measured), sum(map(r.rejects, measured)), sum(map(r.work, measured))) for r in rules]


def plan_order(tried: list[tuple[str, int, int, int]]) -> list[dict]:
    """Each rule's mean cost and rejection share, in the order to run."""
    found = []
    for name, n, rejected, work in tried:
        cost, share = work / max(1, n), (rejected + 0.5) / (n + 1)
        found.append({"rule": name, "cost": cost, "rejection": share, "rank": share / max(cost, 1e-9) if n else 0.0})
    return sorted(found, key=lambda x: -x["rank"])


def sample_trials(documents: DataFrame, rules: tuple[Rule, ...], planning_rows: int) -> list[tuple[str, int, int, int]]:
    """trials() over the texts of the planning_rows rows whose ids' hashes are least, one for each id; texts are measured where they are."""
    drawn = documents.select("doc_id").where("doc_id IS NOT NULL").orderBy(F.xxhash64("doc_id"), "doc_id").limit(planning_rows).distinct()
    texts = documents.select("doc_id", "text").join(F.broadcast(drawn), "doc_id").groupBy("doc_id").agg(F.min("text").alias("text"))

    def run(batches: Iterator[pa.RecordBatch]) -> Iterator[pa.RecordBatch]:
        for batch in batches:
            cols = zip(*trials(texts_as_bytes(batch["text"]), rules), strict=True)
            yield pa.RecordBatch.from_arrays([pa.array(c) for c in cols], ["rule", "n", "rejected", "work"])

    sums = texts.select("text").mapInArrow(tidy(run), "rule string, n long, rejected long, work long").groupBy("rule").agg(*[F.sum(c).alias(c) for c in ("n", "rejected", "work")]).collect()
    by_name = {r["rule"]: (r["rule"], r["n"], r["rejected"], r["work"]) for r in sums}
    return [by_name.get(r.name, (r.name, 0, 0, 0)) for r in rules]


def first_rejection(m: Measured, ordered: list[Rule]) -> str | None:
    return next((x.name for x in ordered if x.rejects(m)), None)


def quality_rules(documents: DataFrame, rules: tuple[Rule, ...] = RULES, planning_rows: int = 200) -> DataFrame:
    """Per document the base measures, base_failed, kept and rejected_by.

    The texts of planning_rows ids are tried to order the rules; they decide cost, and which rule is named, only.
    """
    by_name = {x.name: x for x in rules}
    ordered = [by_name[x["rule"]] for x in plan_order(sample_trials(documents, rules, planning_rows))]
    schema = "doc_id long, n_words long, word_chars long, n_symbols long, n_dup_lines long, n_repeat_words long, base_failed boolean, kept boolean, rejected_by string"
    names = [x.split()[0] for x in schema.split(", ")]

    def start():
        def step(batch: pa.RecordBatch) -> pa.RecordBatch:
            cols: list[list] = [[] for _ in names[1:]]
            for text in texts_as_bytes(batch["text"]):
                m = measure(text)
                base = fails_base(m)
                why = "base" if base else first_rejection(m, ordered)
                for col, x in zip(cols, (len(m.words), m.word_chars, m.n_symbols, m.n_dup_lines, m.n_repeat_words, base, why is None, why), strict=True):
                    col.append(x)
            types = [pa.int64()] * 5 + [pa.bool_()] * 2 + [pa.string()]
            return pa.RecordBatch.from_arrays([batch["doc_id"], *(pa.array(c, t) for c, t in zip(cols, types, strict=True))], names)

        return step

    return map_rows(documents.select(F.col("doc_id").cast("long").alias("doc_id"), "text"), start, schema)
