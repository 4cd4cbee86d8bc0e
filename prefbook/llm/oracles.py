"""DuckDB SQL for the operators' queries."""

WORD = r"[^\x20\x09-\x0D]+"

_WORDS = f"""
texts AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),
listed AS (SELECT r, doc_id, text, regexp_extract_all(text, '{WORD}') AS w FROM texts),
words AS (SELECT r, unnest(w) AS word, generate_subscripts(w, 1) AS i, len(w) AS n FROM listed)"""


def _coverage(width: int) -> str:
    return f"""
g{width} AS (
    SELECT r, i, array_to_string(w[i:i + {width - 1}], ' ') AS g
    FROM (SELECT r, w, unnest(generate_series(1, len(w) - {width - 1})) AS i FROM listed WHERE len(w) >= {width})),
m{width} AS (SELECT r, i, row_number() OVER (PARTITION BY r, g ORDER BY i) > 1 AS later, count(*) OVER (PARTITION BY r, g) > 1 AS twice FROM g{width}),
c{width} AS (
    SELECT r, count(DISTINCT i) AS covered_words, sum(length(word)) AS chars
    FROM (SELECT DISTINCT words.r, words.i, words.word
          FROM m{width} JOIN words ON words.r = m{width}.r AND words.i BETWEEN m{width}.i AND m{width}.i + {width - 1}
          WHERE {"twice" if width == 3 else "later"}) GROUP BY r)"""


_LIMITS = ((5, 15), (6, 14), (7, 13), (8, 12), (9, 11), (10, 10))

_OP2 = (
    "WITH "
    + _WORDS.strip()
    + ","
    + ",".join(_coverage(n) for n in (3, 5, 6, 7, 8, 9, 10)).lstrip()
    + f""",
lines AS (SELECT r, unnest(string_split(text, chr(10))) AS line FROM texts),
full_lines AS (SELECT r, line, count(*) AS k FROM lines WHERE regexp_matches(line, '{WORD}') GROUP BY r, line),
line_sums AS (SELECT r, sum(k - 1) AS n_dup_lines, sum((k - 1) * length(regexp_replace(line, '[\\x20\\x09-\\x0D]+', '', 'g'))) AS dup_line_chars FROM full_lines GROUP BY r),
base AS (
    SELECT l.r, l.doc_id, len(l.w)::BIGINT AS n_words, length(array_to_string(l.w, ''))::BIGINT AS word_chars,
           length(regexp_replace(l.text, '[^#*$%&|<>]+', '', 'g'))::BIGINT AS n_symbols,
           coalesce(s.n_dup_lines, 0)::BIGINT AS n_dup_lines, coalesce(c3.covered_words, 0)::BIGINT AS n_repeat_words,
           coalesce(s.dup_line_chars, 0)::BIGINT AS dup_line_chars,
           {", ".join(f"coalesce(c{n}.chars, 0)::BIGINT AS covered_{n}" for n, _ in _LIMITS)}
    FROM listed l LEFT JOIN line_sums s USING (r) LEFT JOIN c3 USING (r) {" ".join(f"LEFT JOIN c{n} USING (r)" for n, _ in _LIMITS)}),
judged AS (SELECT *, n_words < 50 OR 100 * n_repeat_words > 50 * n_words AS base_failed FROM base)
SELECT doc_id, n_words, word_chars, n_symbols, n_dup_lines, n_repeat_words, base_failed,
       NOT (base_failed OR 100 * dup_line_chars > 20 * word_chars OR 100 * n_symbols > 10 * n_words
            OR {" OR ".join(f"100 * covered_{n} > {most} * word_chars" for n, most in _LIMITS)}) AS kept,
       dup_line_chars, {", ".join(f"covered_{n}" for n, _ in _LIMITS)}
FROM judged"""
)

_FOLD = "translate({}, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz')"

_OP7 = f"""
WITH RECURSIVE listed AS (SELECT row_number() OVER () AS r, doc_id, regexp_extract_all({_FOLD.format("coalesce(text, '')")}, '{WORD}') AS w FROM documents),
shingles AS (
    SELECT DISTINCT r, array_to_string(w[i:i + 4], ' ') AS s
    FROM (SELECT r, w, unnest(generate_series(1, greatest(len(w) - 4, 1))) AS i FROM listed WHERE len(w) > 0)),
sizes AS (SELECT r, count(*) AS n FROM shingles GROUP BY r),
pairs AS (SELECT x.r AS a, y.r AS b, count(*) AS k FROM shingles x JOIN shingles y ON x.s = y.s AND x.r < y.r GROUP BY x.r, y.r),
links AS (SELECT a, b FROM pairs JOIN sizes p ON p.r = a JOIN sizes q ON q.r = b WHERE 100 * k >= 75 * (p.n + q.n - k)),
ways AS (SELECT a, b FROM links UNION SELECT b, a FROM links),
reach AS (SELECT r AS a, r AS b FROM listed UNION SELECT reach.a, ways.b FROM reach JOIN ways ON ways.a = reach.b)
SELECT l.doc_id, coalesce(s.n, 0)::BIGINT AS n_shingles, min(o.doc_id) AS component_id
FROM listed l LEFT JOIN sizes s USING (r) JOIN reach ON reach.a = l.r JOIN listed o ON o.r = reach.b
GROUP BY l.r, l.doc_id, s.n"""

_ALNUM = r"[^\x00-\x2F\x3A-\x60\x7B-\x7F]+"


def _folded(table: str, key: str) -> str:
    return f"SELECT row_number() OVER () AS r, {key}, regexp_extract_all({_FOLD.format("coalesce(text, '')")}, '{_ALNUM}') AS w FROM {table}"


def _runs(source: str, key: str) -> str:
    """Runs of 10 words."""
    return f"SELECT {key}, i, array_to_string(w[i:i + 9], ' ') AS g FROM (SELECT {key}, w, unnest(generate_series(1, len(w) - 9)) AS i FROM {source} WHERE len(w) >= 10)"


_OP8 = f"""
WITH listed AS ({_folded("documents", "doc_id")}),
items AS ({_folded("benchmark", "item_id::VARCHAR AS item_id")}),
windows AS (SELECT DISTINCT item_id, g FROM ({_runs("items", "item_id")})),
short AS (SELECT DISTINCT item_id, len(w) AS m, array_to_string(w, ' ') AS g FROM items WHERE len(w) BETWEEN 1 AND 9),
found AS (
    SELECT r, i, 10 AS m, item_id FROM ({_runs("listed", "r")}) d JOIN windows USING (g)
    UNION ALL
    SELECT r, i, m, item_id
    FROM (SELECT r, w, unnest(generate_series(1, len(w))) AS i FROM listed WHERE len(w) > 0) d JOIN short ON array_to_string(w[i:i + m - 1], ' ') = g AND i + m - 1 <= len(w)),
hit AS (SELECT r, count(*) AS n_hit FROM (SELECT DISTINCT r, unnest(generate_series(i, i + m - 1)) AS k FROM found) GROUP BY r),
named AS (SELECT r, count(*) AS n_items, string_agg(item_id, ',' ORDER BY item_id) AS ids FROM (SELECT DISTINCT r, item_id FROM found) GROUP BY r)
SELECT doc_id, len(w)::BIGINT AS n_words, coalesce(n_hit, 0)::BIGINT AS n_hit, coalesce(n_items, 0)::BIGINT AS n_items,
       sha256(coalesce(ids, '')) AS items_sha256, coalesce(n_hit, 0) > 0 AS contaminated
FROM listed LEFT JOIN hit USING (r) LEFT JOIN named USING (r)"""


def _score(key: str, shard: int) -> str:
    return f"-1.0 / ln((('0x' || substr(md5({key} || '|{shard}'), 1, 13))::BIGINT::DOUBLE + 0.5) / 4503599627370496.0)"


def _best(key: str, shards: int) -> str:
    return f"list_position([{', '.join(_score(key, k) for k in range(shards))}], greatest({', '.join(_score(key, k) for k in range(shards))})) - 1"


#: CRC-32 of a text can't be computed in DuckDB, so the operator's own query has no SQL; its other columns have.
_OP9 = f"""
WITH keyed AS (SELECT doc_id, coalesce(doc_id::VARCHAR, '') AS key, strlen(coalesce(text, ''))::BIGINT + 8 AS size FROM documents)
SELECT doc_id, size, 'key' AS law, ({_best("key", 24)})::INT AS shard, ({_best("key", 25)})::INT AS grown_shard FROM keyed"""

_OP1 = r"""
WITH source AS (
    SELECT conv_id, turn, coalesce(role, '') AS role, coalesce(text, '') AS text FROM conversations
    UNION ALL SELECT -7, 0, 'user', '</s>[INST] ok [/INST]' UNION ALL SELECT -7, 1, 'assistant', '</s>[INST] ok [/INST]'),
sized AS (
    SELECT *, length(role) + length(text) + length(role || text) - length(replace(role || text, chr(92), ''))
           + len(regexp_extract_all(role, '</?s>|<</?SYS>>|\[/?INST\]')) + len(regexp_extract_all(text, '</?s>|<</?SYS>>|\[/?INST\]')) + 17 AS chars
    FROM source),
walked AS (
    SELECT *, sum(chars) OVER w AS so_far, lead(turn) OVER w AS next_turn
    FROM sized WINDOW w AS (PARTITION BY conv_id ORDER BY turn, role, text ROWS UNBOUNDED PRECEDING))
SELECT conv_id, count(*)::BIGINT AS n_turns, sha256(string_agg(role || chr(10) || text || chr(10), '' ORDER BY turn, role, text)) AS turns_sha256,
       coalesce(sum(length(text)) FILTER (WHERE role = 'assistant'), 0)::BIGINT AS loss_chars,
       sha256(coalesce(string_agg(text, '' ORDER BY turn, role, text) FILTER (WHERE role = 'assistant'), '')) AS loss_sha256,
       sum(so_far) FILTER (WHERE role = 'assistant' OR next_turn IS NULL)::BIGINT AS formatted_chars,
       count(*) FILTER (WHERE role = 'assistant' OR next_turn IS NULL)::BIGINT AS n_examples
FROM walked GROUP BY conv_id"""


def _spans(kind: str, rank: int, pattern: str, good: str) -> str:
    """Spans of a pattern's matches: what stands between the matches and the matches before say where one begins."""
    quoted = pattern.replace("'", "''")
    return f"""
m{rank} AS (SELECT r, unnest(f) AS m, generate_subscripts(f, 1) AS i FROM (SELECT r, regexp_extract_all(text, '{quoted}') AS f FROM texts)),
g{rank} AS (SELECT r, unnest(f) AS g, generate_subscripts(f, 1) AS i FROM (SELECT r, string_split_regex(text, '{quoted}') AS f FROM texts)),
s{rank} AS (
    SELECT r, {rank} AS rank, '{kind}' AS kind, a, a + length(m) AS b
    FROM (SELECT r, m, (sum(length(g) + length(m)) OVER (PARTITION BY r ORDER BY i) - length(m))::BIGINT AS a FROM m{rank} JOIN g{rank} USING (r, i))
    WHERE {good})"""


def _base(kinds: list[tuple[str, str, str]], order: str) -> str:
    parts = [_spans(kind, rank, pattern, good).strip() for rank, (kind, pattern, good) in enumerate(kinds)]
    every = " UNION ALL ".join(f"SELECT * FROM s{rank}" for rank in range(len(kinds)))
    counts = ", ".join(f"count(*) FILTER (WHERE kind = '{kind}')::BIGINT AS n_{kind}" for kind, *_ in kinds)
    shown = f"sha256(coalesce(string_agg(kind || ':' || a || ':' || b, ',' ORDER BY {order}), ''))"
    return (
        "WITH texts AS (SELECT row_number() OVER () AS r, doc_id, coalesce(text, '') AS text FROM documents),\n"
        + ",\n".join(parts)
        + f",\nevery AS ({every})\nSELECT doc_id, {counts}, {shown} AS base_sha256 FROM texts LEFT JOIN every USING (r) GROUP BY r, doc_id"
    )


_DIGITS = "regexp_replace(m, '[^0-9]', '', 'g')"
_DIGIT = f"substr({_DIGITS}, length({_DIGITS}) - i + 1, 1)::INT"
_LUHN = f"list_sum(list_transform(range(1, length({_DIGITS}) + 1), lambda i: CASE WHEN i % 2 = 1 THEN {_DIGIT} WHEN {_DIGIT} > 4 THEN 2 * {_DIGIT} - 9 ELSE 2 * {_DIGIT} END)) % 10 = 0"
_PII = _base(
    [
        ("email", r"[A-Za-z0-9._%+-]+@[A-Za-z0-9-]+(?:\.[A-Za-z0-9-]+)+", "true"),
        ("ip", r"[0-9]+(?:\.[0-9]+)(?:\.[0-9]+)(?:\.[0-9]+)", "len(list_filter(string_split(m, '.'), lambda x: length(ltrim(x, '0')) > 3 OR coalesce(try_cast(x AS BIGINT), 0) > 255)) = 0"),
        ("card", r"[0-9](?:[\x20-]?[0-9])+", f"length({_DIGITS}) BETWEEN 16 AND 19 AND {_LUHN}"),
        ("phone", r"\+[0-9][\x20().0-9-]+[0-9]", f"length({_DIGITS}) BETWEEN 8 AND 15"),
    ],
    "rank, a",
)
_ASSIGN = r"""(?i:password|passwd|secret|token|api_?key)["']?\x20*[:=]\x20*["']?([A-Za-z0-9+/_.=-]+)"""
_SECRETS = _base(
    [
        ("assign", _ASSIGN, "length(regexp_extract(m, '" + _ASSIGN.replace("'", "''") + "', 1)) >= 6"),
        ("access", "AKIA[A-Z0-9]+", "length(m) >= 20"),
        ("hex", "[0-9a-f]+", "length(m) >= 24"),
    ],
    "a, rank",
)

SQL: dict[str, str] = {
    "op1_prefix_targets": _OP1,
    "op8_shift_table_search": _OP8,
    "op2_repetition_coverage": _OP2,
    "op7_token_group_join": _OP7,
    "plain_identifiers": _PII,
    "plain_secrets": _SECRETS,
    "rendezvous_shards": _OP9,
}
