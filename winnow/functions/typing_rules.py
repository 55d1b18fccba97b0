"""Token types: word classes and entity shapes by closed lists, endings and shape.

Rules are plain data, from which both the column expression and the SQL text are generated.
"""

from __future__ import annotations

from pyspark.sql import Column
from pyspark.sql import functions as F

#: Closed-class words of four languages, by type, in order of precedence.
CLOSED = {
    "DET": "the a an this that these those der die das ein eine le la les un une du des el los las una".split(),
    "PRON": "i you he she it we they ich du er sie es wir ihr je tu il elle nous vous ils elles yo nosotros ellos".split(),
    "PREP": "of in to for with on at by from as in mit von zu auf für aus à de en dans par pour sur con por para".split(),
    "CONJ": "and or but und oder aber et ou mais y o pero que".split(),
    "AUX": "is are was were be been am ist sind war sein est sont était être es son era ser".split(),
    "NEG": "not no never nicht kein nie ne pas non jamais nunca".split(),
    "WH": "what which who whom whose when where why how wer wie wo wann qui quoi quand où qué quién cuándo dónde".split(),
}
#: Endings of open-class words.
ENDINGS = {
    "NOUN": ("tion", "ment", "heit", "keit", "ung", "ción", "eau"),
    "ADV": ("ly", "lich", "mente"),
    "VERB": ("ing", "ed", "er", "en", "ar", "ir"),
    "ADJ": ("ble", "est", "al", "ig", "oso"),
}
POS = ("NUM", "PUNCT", *CLOSED, *ENDINGS, "ALLCAPS", "PROPN", "SHORT", "OTHER")

#: Shapes of entities in order of precedence, on blank-separated tokens. OTHER is no entity.
ENTITY_SHAPES = {
    "EMAIL": r"^[A-Za-z0-9._%+-]+@[A-Za-z0-9.-]+[.][A-Za-z]{2,}",
    "URL": r"^https?://",
    "IP": r"^[0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[.][0-9]{1,3}[^0-9]*$",
    "HEX": r"^[^0-9a-f]?[0-9a-f]{16,}[^0-9a-f]*$",
    "MONEY": r"^[$€£][0-9]",
    "DATE": r"^[0-9]{4}-[0-9]{2}-[0-9]{2}",
    "PHONE": r"^[+(]?[0-9][0-9() -]{6,}[0-9]$",
    "NUMBER": r"^[0-9]+([.,][0-9]+)?[^\p{L}0-9]*$",
    "LICENCE": r"^(Apache|MIT|GPL|BSD|License|Licensed|Copyright|CC)[^\p{L}]*$",
    "CAPSEQ": r"^\p{Lu}{2,}",
}
ENTITIES = (*ENTITY_SHAPES, "OTHER")
TAGSETS = {"pos": POS, "entity": ENTITIES}
SENTENCE_END = (".", "!", "?", ":")


def _quoted(items) -> str:
    return ", ".join("'" + x.replace("'", "''") + "'" for x in items)


def pos_case(piece: str, before: str, matches: str) -> str:
    """A CASE over a piece and the piece before it; ``matches`` is the dialect's regular-expression predicate."""
    low = f"lower({piece})"
    rule = [f"WHEN {matches}({piece}, '^\\p{{N}}') THEN 'NUM'", f"WHEN NOT {matches}({piece}, '^[\\p{{L}}\\p{{N}}]') THEN 'PUNCT'"]
    rule += [f"WHEN {low} IN ({_quoted(w)}) THEN '{t}'" for t, w in CLOSED.items()]
    rule += [f"WHEN {matches}({low}, '({'|'.join(e)})$') THEN '{t}'" for t, e in ENDINGS.items()]
    rule += [
        f"WHEN {matches}({piece}, '^\\p{{Lu}}{{2,}}$') THEN 'ALLCAPS'",
        f"WHEN {matches}({piece}, '^\\p{{Lu}}') AND {before} NOT IN ({_quoted(SENTENCE_END)}) THEN 'PROPN'",
        f"WHEN length({piece}) <= 3 THEN 'SHORT'",
    ]
    return f"CASE {' '.join(rule)} ELSE 'OTHER' END"


def entity_case(token: str, matches: str) -> str:
    return "CASE " + " ".join(f"WHEN {matches}({token}, '{p}') THEN '{t}'" for t, p in ENTITY_SHAPES.items()) + " ELSE 'OTHER' END"


def pos_tags(pieces: Column) -> Column:
    """Word-class types of an array of pieces; a text's first piece counts as following a sentence end."""
    before = F.slice(F.concat(F.array(F.lit(".")), pieces), F.lit(1), F.size(pieces))
    return F.zip_with(pieces, before, _pos_of)


def _pos_of(piece: Column, before: Column) -> Column:
    low = F.lower(piece)
    out = F.when(piece.rlike(r"^\p{N}"), "NUM").when(~piece.rlike(r"^[\p{L}\p{N}]"), "PUNCT")
    for t, w in CLOSED.items():
        out = out.when(low.isin(w), t)
    for t, e in ENDINGS.items():
        out = out.when(low.rlike(f"({'|'.join(e)})$"), t)
    return (
        out.when(piece.rlike(r"^\p{Lu}{2,}$"), "ALLCAPS")
        .when(piece.rlike(r"^\p{Lu}") & ~before.isin(*SENTENCE_END), "PROPN")
        .when(F.length(piece) <= 3, "SHORT")
        .otherwise("OTHER")
    )


def entity_tags(tokens: Column) -> Column:
    def of(token: Column) -> Column:
        out = None
        for t, p in ENTITY_SHAPES.items():
            out = F.when(token.rlike(p), t) if out is None else out.when(token.rlike(p), t)
        return out.otherwise("OTHER")

    return F.transform(tokens, of)
