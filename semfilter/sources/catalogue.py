"""The planted query catalogue: predicates whose answers are known, as SQL of either engine."""

from __future__ import annotations

from dataclasses import dataclass


class Spark:
    """How Spark spells what the two engines spell differently."""

    name = "spark"

    @staticmethod
    def uniform(key: str) -> str:
        return f"(CAST(conv(substr(md5({key}), 1, 8), 16, 10) AS DOUBLE) / 4294967296D)"

    @staticmethod
    def match(col: str, pattern: str) -> str:
        return f"({col} RLIKE '{pattern}')"

    @staticmethod
    def strip(col: str, pattern: str) -> str:
        return f"regexp_replace({col}, '{pattern}', '')"

    @staticmethod
    def tokens(col: str, pattern: str) -> str:
        return f"filter(split({col}, '{pattern}'), x -> x <> '')"

    count = staticmethod(lambda a: f"size({a})")
    distinct = staticmethod(lambda a: f"array_distinct({a})")


class Duck:
    """The same in DuckDB."""

    name = "duck"

    @staticmethod
    def uniform(key: str) -> str:
        return f"(CAST(('0x' || substr(md5({key}), 1, 8)) AS BIGINT) / 4294967296.0::DOUBLE)"

    @staticmethod
    def match(col: str, pattern: str) -> str:
        return f"regexp_matches({col}, '{pattern}')"

    @staticmethod
    def strip(col: str, pattern: str) -> str:
        return f"regexp_replace({col}, '{pattern}', '', 'g')"

    @staticmethod
    def tokens(col: str, pattern: str) -> str:
        return f"list_filter(regexp_split_to_array({col}, '{pattern}'), lambda x: x <> '')"

    count = staticmethod(lambda a: f"len({a})")
    distinct = staticmethod(lambda a: f"list_distinct({a})")


@dataclass(frozen=True)
class Planted:
    """A predicate: what it asks, its logit over a document's columns, and the weight of the noise."""

    qid: str
    asks: str
    logit: str
    noise: float
    kind: str


def flag(cond: str, weight: float) -> str:
    return f"({weight} * CASE WHEN {cond} THEN 1 ELSE -1 END)"


# The lexicon of the toxic texts.
LEXICON = ("trash", "idiot", "scum", "clown", "worthless", "moron", "pathetic", "loser", "stupid", "disgusting")


def catalogue(d=Spark) -> dict[str, Planted]:
    """The twenty predicates on documents, in one engine's spelling."""
    lex = d.match("lower(text)", "|".join(LEXICON))
    words, low = d.tokens("text", "[ \\n\\t]+" if d is Duck else r"[ \\n\\t]+"), d.tokens("lower(text)", "[^a-zà-ÿ]+")
    mean_len = f"(length({d.strip('text', '[ \\n\\t]+' if d is Duck else r'[ \\n\\t]+')}) * 1.0e0 / greatest({d.count(words)}, 1))"
    ratio = f"({d.count(d.distinct(low))} * 1.0e0 / greatest({d.count(low)}, 1))"
    vowels = f"((length(text) - length({d.strip('lower(text)', '[aeiou]')})) * 1.0e0 / greatest(length(text), 1))"
    odd = "CAST(substr(source, 4) AS INT) % 2 = 1"
    rows = (
        ("Q01", "written in German", flag("lang = 'de'", 6), 0.5, "topical"),
        ("Q02", "written in English", flag("lang = 'en'", 6), 0.5, "topical"),
        ("Q03", "written in French or Spanish", flag("lang IN ('fr', 'es')", 5), 0.5, "topical"),
        ("Q04", "a long document", "(4 * (ln(greatest(n_chars, 1)) - ln(2000)))", 0.5, "graded"),
        ("Q05", "a short note", "(4 * (ln(500) - ln(greatest(n_chars, 1))))", 0.5, "graded"),
        ("Q06", "states a number", flag(d.match("text", "[0-9]"), 4), 0.5, "token"),
        ("Q07", "insults someone", flag(lex, 5), 0.5, "token"),
        ("Q08", "insults someone, unsure oracle", flag(lex, 2), 1.0, "token"),
        ("Q09", "has a contact address", flag("text LIKE '%@%'", 5), 0.5, "token"),
        ("Q10", "has a license statement", flag("text LIKE '%licen%'", 5), 0.5, "token"),
        ("Q11", "contains junk runs", flag("contains(text, '%%%') OR contains(text, '###') OR contains(text, '***')", 5), 0.5, "token"),
        ("Q12", "is a table", flag("contains(text, ' | ')", 5), 0.5, "token"),
        ("Q13", "repeats a benchmark passage", flag("has_passage", 5), 0.5, "cross"),
        ("Q14", "has an exact copy elsewhere", flag("n_copies > 1", 3), 1.0, "cross"),
        ("Q15", "uses long words", f"(3 * ({mean_len} - 6.4))", 0.5, "graded"),
        ("Q16", "is repetitive", f"(25 * (0.55 - {ratio}))", 0.5, "graded"),
        ("Q17", "is rich in vowels", f"(60 * ({vowels} - 0.37))", 0.5, "graded"),
        ("Q18", "comes from an odd-numbered source", flag(odd, 4), 1.0, "hidden"),
        ("Q19", "English, without digits, over 1000 characters", flag(f"lang = 'en' AND NOT {d.match('text', '[0-9]')} AND n_chars > 1000", 3), 1.0, "conjunction"),
        ("Q20", "a coin toss", "0.0e0", 1.5, "noise"),
    )
    return {r[0]: Planted(*r) for r in rows}


ALL = tuple(f"Q{k:02d}" for k in range(1, 21))


def normal(key: str, tag: str, d=Spark) -> str:
    """A hashed draw, nearly normal: four uniforms, centred and scaled."""
    return "((" + " + ".join(d.uniform(f"concat({key}, ':{tag}{j}')") for j in range(1, 5)) + " - 2) * sqrt(3))"


def rich(d=Spark, need: tuple[str, ...] = ALL) -> str:
    """Documents with the two features that look beyond the row, each only if some predicate asks for it."""
    passage = "EXISTS (SELECT 1 FROM benchmark b WHERE contains(documents.text, b.text))" if "Q13" in need else "false"
    copies = "count(*) OVER (PARTITION BY md5(text))" if "Q14" in need else "1"
    return f"SELECT doc_id, text, lang, source, n_chars, {passage} AS has_passage, {copies} AS n_copies FROM documents"


def p_star(q: Planted, d=Spark) -> str:
    """The oracle's probability of yes."""
    return f"(1.0e0 / (1.0e0 + exp(-({q.logit} + {q.noise} * {normal(f'CAST(doc_id AS VARCHAR(20)), {chr(39)}:{q.qid}{chr(39)}', 'g', d)}))))"


def answer(q: str, p: str, mode: str = "argmax", d=Spark) -> str:
    """The oracle's answer: the likelier class, or a hashed draw with that probability."""
    if mode == "argmax":
        return f"CASE WHEN {p} >= 0.5 THEN 1 ELSE 0 END"
    return f"CASE WHEN {d.uniform(f'concat(CAST(doc_id AS VARCHAR(20)), {chr(39)}:{q}:draw{chr(39)})')} < {p} THEN 1 ELSE 0 END"


def prebuilt_p(p: str, qid: str, d=Spark, shrink: float = 0.7, noise: float = 0.8) -> str:
    """A pre-trained scorer's probability: the oracle's logit shrunk, with noise of its own."""
    return f"(1.0e0 / (1.0e0 + exp(-({shrink} * ln({p} / (1.0e0 - {p})) + {noise} * {normal(f'CAST(doc_id AS VARCHAR(20)), {chr(39)}:{qid}{chr(39)}', 's', d)}))))"


def truth_sql(d=Spark, queries: tuple[str, ...] = ALL, mode: str = "argmax", prebuilt: bool = False) -> str:
    """``query_id, doc_id, p_star, y, tokens`` (and ``prob`` of the prebuilt scorer) of some predicates on all documents."""
    cat = catalogue(d)
    n_words = f"CAST({d.count(d.tokens('text', ' '))} AS BIGINT)"
    ps = ", ".join(f"{p_star(cat[q], d)} AS p_{q}" for q in queries)
    wide = f"SELECT doc_id, {n_words} AS tokens, {ps} FROM ({rich(d, queries)}) documents"
    parts = " UNION ALL ".join(f"SELECT '{q}' AS query_id, doc_id, tokens, p_{q} AS p_star, {answer(q, f'p_{q}', mode, d)} AS y{', ' + prebuilt_p(f'least(greatest(p_{q}, 1e-12), 1 - 1e-12)', q, d) + ' AS prob' if prebuilt else ''} FROM wide_truth" for q in queries)
    return f"WITH wide_truth AS ({wide}) SELECT query_id, doc_id, p_star, CAST(y AS INT) AS y, tokens{', prob' if prebuilt else ''} FROM ({parts}) planted_truth"
