"""SQL text for the registered queries, put together from named common table expressions."""

from __future__ import annotations

import re

from winnow.functions.typing_rules import entity_case, pos_case
from winnow.functions.textops import PIECE, WORD

_W = f"regexp_extract_all(lower(text), '{WORD}')"


def uniform(key: str, seed: int | str) -> str:
    return f"(('0x' || substr(md5({key} || ':{seed}'), 1, 13))::BIGINT / 4503599627370496e0)"


CTE = {
    "corpus": "SELECT * FROM documents WHERE doc_id IN (SELECT min(doc_id) FROM documents GROUP BY text)",
    "tok": f"SELECT doc_id, unnest({_W}) AS term FROM corpus",
    "postok": f"SELECT doc_id, unnest({_W}) AS term, generate_subscripts({_W}, 1) AS pos FROM corpus",
    "len": "SELECT doc_id, count(*)::BIGINT AS n_tokens FROM tok GROUP BY doc_id",
    "tf": "SELECT doc_id, term, count(*)::DOUBLE AS n FROM tok GROUP BY ALL",
    "stok": f"SELECT item_id AS seed_id, unnest({_W}) AS term FROM benchmark",
    "sunit": "SELECT seed_id, term, w / sqrt(sum(w * w) OVER (PARTITION BY seed_id)) AS w FROM (SELECT seed_id, term, count(*)::DOUBLE AS w FROM stok GROUP BY ALL)",
    "centre": "SELECT term, sum(w) / (SELECT count(DISTINCT seed_id) FROM stok)::DOUBLE AS w FROM sunit GROUP BY term",
    "sim": "SELECT doc_id, round(coalesce(sum(n * w), 0) / (sqrt(sum(n * n)) * (SELECT sqrt(sum(w * w)) FROM centre)), 9) AS similarity FROM tf LEFT JOIN centre USING (term) GROUP BY doc_id",
    "lm1": f"SELECT term, count(*) AS c FROM (SELECT unnest({_W}) AS term FROM conversations) GROUP BY term",
    "lmt": "SELECT sum(c)::DOUBLE AS n, count(*)::DOUBLE AS v FROM lm1",
    "ppl": "SELECT doc_id, round(exp(-sum(ln((coalesce(c, 0) + 1e0) / (n + v + 1e0))) / count(*)), 9) AS perplexity FROM tok LEFT JOIN lm1 USING (term) CROSS JOIN lmt GROUP BY doc_id",
    "cpos": f"SELECT conv_id, turn, unnest({_W}) AS term, generate_subscripts({_W}, 1) AS pos FROM conversations",
    "lm2": "SELECT prev, term, count(*) AS c2 FROM (SELECT term, lag(term) OVER (PARTITION BY conv_id, turn ORDER BY pos) AS prev FROM cpos) WHERE prev IS NOT NULL GROUP BY ALL",
    "bip": "SELECT doc_id, pos, CASE WHEN b.c > 0 THEN 0.5e0 * coalesce(c2, 0) / b.c + 0.5e0 * p1 ELSE p1 END AS p FROM (SELECT t.*, (coalesce(a.c, 0) + 1e0) / (n + v + 1e0) AS p1 FROM (SELECT doc_id, pos, term, lag(term) OVER (PARTITION BY doc_id ORDER BY pos) AS prev FROM postok) t LEFT JOIN lm1 a USING (term) CROSS JOIN lmt) x LEFT JOIN lm1 b ON x.prev = b.term LEFT JOIN lm2 ON x.prev = lm2.prev AND x.term = lm2.term",
    "ppl2": "SELECT doc_id, exp(-sum(ln(p)) / count(*)) AS perplexity FROM bip GROUP BY doc_id",
    "piece": f"SELECT doc_id, unnest(regexp_extract_all(text, '{PIECE}')) AS piece, generate_subscripts(regexp_extract_all(text, '{PIECE}'), 1) AS pos FROM corpus",
    "tag": f"SELECT doc_id, {pos_case('piece', 'before', 'regexp_matches')} AS tok_type FROM (SELECT doc_id, piece, coalesce(lag(piece) OVER (PARTITION BY doc_id ORDER BY pos), '.') AS before FROM piece)",
    "typed": "SELECT doc_id, tok_type, count(*) AS n FROM tag GROUP BY ALL",
    "ent": "SELECT doc_id, round((greatest(-sum(n / t * ln(n / t)), 0) + 0e0), 9) AS entropy FROM (SELECT doc_id, n::DOUBLE AS n, (sum(n) OVER (PARTITION BY doc_id))::DOUBLE AS t FROM typed) GROUP BY doc_id",
    "etag": f"SELECT doc_id, {entity_case('tok', 'regexp_matches')} AS tok_type FROM (SELECT doc_id, unnest(regexp_extract_all(text, '[^ \\t\\r\\n]+')) AS tok FROM corpus)",
    "metrics": "SELECT doc_id, coalesce(n_tokens, 0) AS n_tokens, coalesce(similarity, 0) AS similarity, perplexity, entropy FROM (SELECT doc_id FROM corpus) LEFT JOIN len USING (doc_id) LEFT JOIN sim USING (doc_id) LEFT JOIN ppl USING (doc_id) LEFT JOIN ent USING (doc_id)",
    "budget": "SELECT floor(0.1e0 * sum(n_tokens))::BIGINT AS b FROM metrics",
    "quant": "SELECT *, ceil(100e0 * (cume_dist() OVER (ORDER BY similarity))) / 100e0 AS q_similarity, CASE WHEN perplexity IS NOT NULL THEN ceil(100e0 * (count(perplexity) OVER (ORDER BY perplexity NULLS LAST))::DOUBLE / (count(perplexity) OVER ())) / 100e0 END AS q_perplexity, CASE WHEN entropy IS NOT NULL THEN ceil(100e0 * (count(entropy) OVER (ORDER BY entropy NULLS LAST))::DOUBLE / (count(entropy) OVER ())) / 100e0 END AS q_entropy FROM metrics",
    "blend": "SELECT *, (1e0 * q_similarity + 1e0 * q_perplexity + 1e0 * q_entropy) / 3e0 AS blended FROM quant",
    "lab": "SELECT task, doc_id, text, label FROM (SELECT 'quality' AS task, d.doc_id, d.text, quality::VARCHAR AS label FROM documents d JOIN labels l USING (doc_id) UNION ALL SELECT 'toxic', d.doc_id, d.text, toxic::VARCHAR FROM documents d JOIN labels l USING (doc_id))",
    "pool": f"SELECT * FROM (SELECT *, row_number() OVER (PARTITION BY task ORDER BY {uniform('doc_id', 7)}, doc_id) AS rank FROM lab)",
}


def hard_body(column: str, source: str = "metrics", overshoot: str = "exclude", fraction: str = "0.1e0") -> str:
    """The chosen ids with their running tokens."""
    test = "cum_tokens <= b" if overshoot == "exclude" else "cum_tokens - n_tokens < b"
    return (
        f"SELECT doc_id, n_tokens, cum_tokens::BIGINT AS cum_tokens FROM (SELECT doc_id, n_tokens, sum(n_tokens) OVER (ORDER BY round({column}, 9) DESC, doc_id ROWS UNBOUNDED PRECEDING) AS cum_tokens "
        f"FROM {source} WHERE {column} IS NOT NULL) CROSS JOIN (SELECT floor({fraction} * sum(n_tokens))::BIGINT AS b FROM metrics) WHERE {test}"
    )


def soft_body(weight: str, source: str, seed: int = 7) -> str:
    u = f"greatest({uniform('doc_id', seed)}, pow(2e0, -53))"
    return hard_body("score", f"(SELECT doc_id, n_tokens, -round(-ln({u}) / {weight}, 9) AS score FROM {source} WHERE {weight} > 0)")


def sql(body: str, **extra: str) -> str:
    """``body`` with every expression it names, directly or through others."""
    known = CTE | extra
    order: list[str] = []
    open_: list[str] = []

    def need(text: str) -> None:
        for name in known:
            if name not in order and name not in open_ and re.search(rf"\b(FROM|JOIN)\s+{name}\b", text):
                open_.append(name)
                need(known[name])
                order.append(name)

    need(body)
    return ("WITH " + ",\n".join(f"{n} AS ({known[n]})" for n in order) + "\n" if order else "") + body
