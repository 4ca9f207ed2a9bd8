"""DuckDB SQL for the queries of this subpackage that SQL can express."""

from __future__ import annotations

from .chat import ChatTemplate
from .licenses import ANCHORS, RULES, SENTENCES, normal
from .quality import QualityRules

WORD = r"[^\x20\x09-\x0D]+"
SPACES = "chr(32)||chr(9)||chr(10)||chr(11)||chr(12)||chr(13)"


def quoted(text: str) -> str:
    return "'" + text.replace("'", "''") + "'"


def op1() -> str:
    t = ChatTemplate()
    special = f"(length(x) - length(translate(x, '<#\\', '')))"
    escaped = f"(length(text) + {special.replace('x', 'text')})"
    role = f"(length(role) + length(role) - length(translate(role, '<#\\' || chr(10), '')))"
    said = r"'\### Assistant: </turn> ok'"
    return f"""
    WITH every AS (
      SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
      UNION ALL SELECT -7, 0, 'user', {said} UNION ALL SELECT -7, 1, 'assistant', {said}),
    ranked AS (
      SELECT *, row_number() OVER w - 1 AS pos, lag(role) OVER w AS before, row_number() OVER (PARTITION BY conv_id ORDER BY turn DESC, role DESC, text DESC) AS back
      FROM every WINDOW w AS (PARTITION BY conv_id ORDER BY turn NULLS FIRST, role, text)),
    judged AS (
      SELECT *, CASE WHEN before IS NULL THEN role IN ('system', 'user') WHEN before IN ('system', 'assistant') THEN role = 'user'
                     WHEN before = 'user' THEN role = 'assistant' ELSE false END AS fine FROM ranked)
    SELECT conv_id, count(*) AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY pos)) AS turns_sha256,
           CAST(coalesce(sum(length(text)) FILTER (role = 'assistant'), 0) AS BIGINT) AS loss_chars,
           sha256(coalesce(string_agg(text, '' ORDER BY pos) FILTER (role = 'assistant'), '')) AS loss_sha256,
           CAST(sum({len(t.opens)} + {role} + {len(t.names_end)} + {escaped} + {len(t.closes)}) AS BIGINT) AS formatted_chars,
           bool_and(fine) AND max(CASE WHEN back = 1 THEN role END) = 'assistant' AS valid,
           CAST(min(pos) FILTER (NOT fine) AS INTEGER) AS bad_turn
    FROM judged GROUP BY conv_id"""


def op3(bits_left: int = 24) -> str:
    return rf"""
    WITH sized AS (
      SELECT doc_id, source, len(regexp_extract_all(coalesce(text, ''), '{WORD}')) AS size,
             ('0x' || substr(md5(coalesce(doc_id::VARCHAR, '')), 1, 15))::BIGINT >> {bits_left} AS cell FROM documents),
    per AS (SELECT source, sum(size)::BIGINT AS source_size FROM sized GROUP BY source),
    weighed AS (
      SELECT *, source_size * 3 AS cap, (row_number() OVER (ORDER BY source NULLS LAST) - 1) % 3 + 1 AS weight, sum(source_size) OVER () AS total FROM per),
    levels AS (
      SELECT *, (total - coalesce(sum(cap) OVER (w ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0))::DOUBLE
                / sum(weight) OVER (w ROWS BETWEEN CURRENT ROW AND UNBOUNDED FOLLOWING) AS level
      FROM weighed WINDOW w AS (ORDER BY cap::DOUBLE / weight, source NULLS LAST)),
    goal AS (SELECT source, source_size, least(cap::DOUBLE, max(level) OVER () * weight) AS target FROM levels),
    plan AS (SELECT *, CASE WHEN source_size > 0 THEN floor(target / source_size)::BIGINT ELSE 0 END AS whole FROM goal),
    budget AS (SELECT *, target - whole * source_size AS rest FROM plan),
    cells AS (SELECT source, cell, sum(size) AS here FROM sized GROUP BY source, cell),
    run AS (
      SELECT c.source, cell, here, sum(here) OVER (PARTITION BY c.source ORDER BY cell) AS upto, rest
      FROM cells c JOIN budget b ON c.source IS NOT DISTINCT FROM b.source),
    edge AS (SELECT source, min(cell) AS cell FROM run WHERE upto > rest AND rest > 0 GROUP BY source),
    cut AS (
      SELECT e.source, CASE WHEN upto - rest < rest - (upto - here) THEN e.cell ELSE e.cell - 1 END AS last
      FROM edge e JOIN run r ON e.source IS NOT DISTINCT FROM r.source AND e.cell = r.cell)
    SELECT s.doc_id, s.size::BIGINT AS size, b.source_size, b.target,
           (s.size * (b.whole + CASE WHEN s.cell <= c.last THEN 1 ELSE 0 END))::BIGINT AS taken,
           (b.whole + CASE WHEN s.cell <= c.last THEN 1 ELSE 0 END)::BIGINT AS copies
    FROM sized s JOIN budget b ON s.source IS NOT DISTINCT FROM b.source LEFT JOIN cut c ON s.source IS NOT DISTINCT FROM c.source"""


def op6() -> str:
    r = QualityRules()
    return rf"""
    WITH docs AS (SELECT row_number() OVER () AS k, doc_id, source AS host, coalesce(text, '') AS text FROM documents),
    words AS (SELECT k, regexp_extract_all(text, '{WORD}') AS ws FROM docs),
    windows AS (
      SELECT k, pos, ws[pos] || ' ' || ws[pos + 1] || ' ' || ws[pos + 2] AS w
      FROM (SELECT k, ws, unnest(range(1, len(ws) - 1)) AS pos FROM words WHERE len(ws) >= 3)),
    doubled AS (SELECT k, pos FROM (SELECT k, pos, count(*) OVER (PARTITION BY k, w) AS n FROM windows) WHERE n > 1),
    covered AS (SELECT k, count(DISTINCT pos + d) AS n FROM doubled, (SELECT unnest([0, 1, 2]) AS d) GROUP BY k),
    lines AS (
      SELECT k, count(*) AS n, count(*) - count(DISTINCT line) AS dup FROM (SELECT k, unnest(string_split(text, chr(10))) AS line FROM docs)
      WHERE translate(line, {SPACES}, '') <> '' GROUP BY k),
    told AS (
      SELECT doc_id, host, len(ws)::BIGINT AS n_words, length(translate(text, {SPACES}, ''))::BIGINT AS word_chars,
             (length(text) - length(translate(text, '#*$%&|<>', '')))::BIGINT AS n_symbols,
             coalesce(l.n, 0)::BIGINT AS n_lines, coalesce(l.dup, 0)::BIGINT AS n_dup_lines, coalesce(c.n, 0)::BIGINT AS n_repeat_words
      FROM docs JOIN words USING (k) LEFT JOIN lines l USING (k) LEFT JOIN covered c USING (k)),
    judged AS (
      SELECT *, n_words < {r.least_words} OR 100 * n_repeat_words > {r.most_repeat_percent} * n_words AS base_failed,
             100 * n_symbols > {r.most_symbols_per_100_words} * n_words OR 100 * n_dup_lines > {r.most_dup_line_percent} * n_lines
             OR word_chars < {r.least_word_chars} * n_words OR word_chars > {r.most_word_chars} * n_words AS soft_failed FROM told),
    hosts AS (SELECT host, count(*) AS n, sum((base_failed OR soft_failed)::INT) AS bad FROM judged GROUP BY host),
    moments AS (SELECT avg(bad / n) AS m, var_pop(bad / n) AS v FROM hosts),
    prior AS (SELECT m, CASE WHEN v > 1e-9 AND m > 0 AND m < 1 THEN greatest(m * (1 - m) / v - 1, 1e-3) ELSE 1e6 END AS s FROM moments),
    shrunk AS (SELECT host, (bad + m * s) / (n + s) AS rate FROM hosts, prior),
    flagged AS (SELECT host, rate > (SELECT least({r.host_rate}, avg(rate) + {r.host_z} * stddev_pop(rate) + 1e-9) FROM shrunk) AS host_flagged FROM shrunk)
    SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed, NOT base_failed AND NOT (host_flagged AND soft_failed) AS kept
    FROM judged JOIN flagged ON judged.host IS NOT DISTINCT FROM flagged.host"""


def op8() -> str:
    group = "substr('ABCDEFGHIJKLMNOPQRSTUVWXYZ234567', 1 + (((('0x' || substr(hex, (i * 5) // 4 + 1, 2))::INT >> (3 - (i * 5) % 4)) & 31)), 1)"
    return f"""
    WITH told AS (SELECT page_id, coalesce(html, '') AS body FROM pages),
    hashed AS (SELECT page_id, octet_length(encode(body)) AS n, sha1(body) AS hex FROM told),
    tops AS (SELECT hex, n, max(page_id) AS top FROM hashed GROUP BY hex, n)
    SELECT page_id, n::BIGINT AS payload_bytes, array_to_string(list_transform(range(32), lambda i: {group}), '') AS payload_digest,
           CASE WHEN page_id < top THEN 'revisit' ELSE 'response' END AS record_type, CASE WHEN page_id < top THEN top END AS refers_to
    FROM hashed JOIN tops USING (hex, n)"""


def op9() -> str:
    known = ", ".join(f"({quoted(n)}, {quoted(k)})" for n, k in {normal(s): k for k, s in SENTENCES}.items())
    likely = " OR ".join(f"contains(lower(s), {quoted(a)})" for a in ANCHORS)
    rest, steps = "raw", []
    for i, (_, seq) in enumerate(RULES):
        sequence = quoted("," + ",,".join(seq) + ",")
        steps.append(f"r{i} AS (SELECT *, replace({rest}, {sequence}, '|') AS rest{i}, ((length({rest}) - length(replace({rest}, {sequence}, '|'))) // (length({sequence}) - 1)) AS n{i} FROM {'found' if i == 0 else f'r{i - 1}'})")
        rest = f"rest{i}"
    names = ", ".join(f"CASE WHEN n{i} > 0 THEN {quoted(name)} END" for i, (name, _) in enumerate(RULES))
    last = len(RULES) - 1
    return rf"""
    WITH known(norm, kind) AS (VALUES {known}),
    docs AS (SELECT row_number() OVER () AS k, doc_id, string_split(regexp_replace(coalesce(text, ''), '([.!?:])[ \t\r]+', '\1' || chr(10), 'g'), chr(10)) AS parts FROM documents),
    hits AS (
      SELECT k, pos, kind FROM (SELECT k, unnest(parts) AS s, generate_subscripts(parts, 1) AS pos FROM docs) p
      JOIN known ON norm = trim(regexp_replace(lower(s), '[^a-z0-9]+', ' ', 'g')) WHERE {likely}),
    found AS (
      SELECT k, doc_id, count(kind) AS n, coalesce(string_agg(kind, ',' ORDER BY pos), '') AS ids, coalesce(string_agg(',' || kind || ',', '' ORDER BY pos), '') AS raw
      FROM docs LEFT JOIN hits USING (k) GROUP BY k, doc_id),
    {", ".join(steps)}
    SELECT doc_id, n::BIGINT AS n_sentences, ids AS sentence_ids, array_to_string(list_filter([{names}], lambda x, i: x IS NOT NULL AND list_position([{names}], x) = i), ',') AS licenses,
           ({" + ".join(f"n{i}" for i in range(last + 1))})::BIGINT AS n_licenses
    FROM r{last}"""


def op10() -> str:
    return """
    WITH RECURSIVE v AS (
      SELECT vec_id, label, embedding::DOUBLE[] AS e FROM embeddings),
    fit AS (
      SELECT * FROM v WHERE label IS NOT NULL AND e IS NOT NULL AND len(list_filter(e, lambda x: x IS NULL OR NOT isfinite(x))) = 0 AND len(list_filter(e, lambda x: x <> 0)) > 0),
    link AS (
      SELECT a.vec_id AS x, b.vec_id AS y FROM fit a JOIN fit b ON a.label = b.label AND a.vec_id <> b.vec_id
      WHERE list_inner_product(a.e, b.e) / (sqrt(list_inner_product(a.e, a.e)) * sqrt(list_inner_product(b.e, b.e))) >= 0.98),
    reach AS (SELECT vec_id AS x, vec_id AS y FROM v UNION SELECT r.x, l.y FROM reach r JOIN link l ON r.y = l.x),
    named AS (SELECT x AS vec_id, min(y) AS component_id FROM reach GROUP BY x),
    counted AS (SELECT x AS vec_id, count(*) AS n FROM link GROUP BY x)
    SELECT vec_id, coalesce(n, 0)::BIGINT AS n_links, component_id, vec_id = component_id AS kept FROM named LEFT JOIN counted USING (vec_id)"""


def all_oracles() -> dict[str, str]:
    return {"op1_chat": op1(), "op3_mixing": op3(), "op6_quality": op6(), "op8_warc": op8(), "op9_licenses": op9(), "op10_embeddings": op10()}
