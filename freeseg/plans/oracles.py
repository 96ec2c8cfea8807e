"""The workloads as DuckDB SQL over the same tables, put together from named steps."""

from __future__ import annotations

from . import workloads as w

DOCS = "docs AS (SELECT lang, doc_id, text FROM documents)"
TRAIN_DOCS = """docs AS (SELECT d.lang, d.doc_id, d.text FROM documents d WHERE d.doc_id % 10 <> 0
    AND NOT EXISTS (SELECT 1 FROM benchmark b WHERE length(b.text) > 0 AND contains(d.text, b.text)))"""
ITEMS = "SELECT 'en' AS lang, 'b' || item_id AS stmt_id, CAST(item_id % 2 AS INTEGER) AS half, replace(text, chr(10), ' ') AS text FROM benchmark WHERE length(text) > 0"


def document_statements(where: str = "true") -> str:
    return f"""SELECT lang, 'd' || doc_id || ':' || (no - 1) AS stmt_id, CAST(CAST(floor(doc_id / 10) AS BIGINT) % 2 AS INTEGER) AS half, text FROM (
        SELECT lang, doc_id, unnest(string_split(text, chr(10))) AS text, unnest(range(1, len(string_split(text, chr(10))) + 1)) AS no FROM documents WHERE {where}) WHERE text <> ''"""


STATEMENTS = f"stmts AS MATERIALIZED ({ITEMS} UNION ALL {document_statements('doc_id % 10 = 0')})"
CORPUS = f"stmts AS MATERIALIZED ({document_statements()})"
BENCHMARK = f"stmts AS MATERIALIZED ({ITEMS})"


def lines(where: str = "true", name: str = "lines", docs: str = "docs") -> str:
    return f"{name} AS (SELECT lang, line FROM (SELECT lang, unnest(string_split(text, chr(10))) AS line FROM {docs} WHERE {where}) WHERE line <> '')"


def grams(n_max: int, name: str = "grams", source: str = "lines") -> str:
    ranks = ", ".join(f"({n})" for n in range(1, n_max + 1))
    return f"""{name} AS (SELECT lang, n, substr(line, i, n) AS gram, count(*) AS cnt FROM (
        SELECT lang, line, n, unnest(range(1, length(line) - n + 2)) AS i FROM {source}, (VALUES {ranks}) t(n)) GROUP BY ALL)"""


def edges(name: str = "edges", source: str = "grams") -> str:
    return f"""{name} AS (SELECT lang, n - 1 AS n, 'f' AS dir, left(gram, n - 1) AS gram, right(gram, 1) AS nbr, cnt FROM {source} WHERE n > 1
        UNION ALL SELECT lang, n - 1, 'b', substr(gram, 2), left(gram, 1), cnt FROM {source} WHERE n > 1)"""


def wide_edges(ranks, name: str = "wide", source: str = "grams") -> str:
    each = " UNION ALL ".join(f"""SELECT lang, {n} AS n, 'f' AS dir, left(gram, {n}) AS gram, right(gram, {n}) AS nbr, cnt FROM {source} WHERE n = {2 * n}
        UNION ALL SELECT lang, {n}, 'b', right(gram, {n}), left(gram, {n}), cnt FROM {source} WHERE n = {2 * n}""" for n in ranks)
    return f"{name} AS ({each})"


def rated(suffix: str = "", source: str = "edges", name: str = "rated") -> str:
    return f"""{name}{suffix} AS MATERIALIZED (SELECT e.*, max(e.cnt) OVER (PARTITION BY e.lang, e.n, e.dir, e.gram) AS emax, v.cnt AS vcnt, v.vmax FROM {source}{suffix} e
        JOIN (SELECT *, max(cnt) OVER (PARTITION BY lang, n) AS vmax FROM grams{suffix}) v ON v.lang = e.lang AND v.n = e.n AND v.gram = e.gram)"""


def levels(thetas) -> str:
    return "(VALUES " + ", ".join(f"(CAST({t!r} AS DOUBLE))" for t in thetas) + ") l(theta)"


def model(n_max: int, suffix: str = "", source: str = "lines") -> list[str]:
    return [grams(n_max, f"grams{suffix}", source), edges(f"edges{suffix}", f"grams{suffix}"), rated(suffix)]


HELD = "cnt >= theta * emax AND vcnt >= theta * vmax"


def gaps(ranks, stmts: str = "stmts", name: str = "gaps", wide: bool = False) -> str:
    """The gram and what stands across each gap, where the gram fits. wide: across stands as much as the gram."""
    some = ", ".join(f"({n})" for n in ranks)
    w = "n" if wide else "1"
    return f"""{name} AS MATERIALIZED (SELECT * FROM (SELECT lang, stmt_id, n, gap, dir, CASE WHEN dir = 'f' AND gap >= n THEN substr(text, gap - n + 1, n)
            WHEN dir = 'b' AND gap + n <= length(text) THEN substr(text, gap + 1, n) END AS gram,
        CASE WHEN dir = 'f' AND gap + {w} <= length(text) THEN substr(text, gap + 1, {w}) WHEN dir = 'b' AND gap >= {w} THEN substr(text, gap - {w} + 1, {w}) END AS nbr
        FROM (SELECT lang, stmt_id, text, CAST(unnest(range(1, length(text))) AS INTEGER) AS gap FROM {stmts}), (VALUES {some}) t(n), (VALUES ('f'), ('b')) d(dir)) WHERE gram IS NOT NULL)"""


def base(kind: str, theta: float, suffix: str = "", gap_rows: str = "gaps", name: str = "prof", from_: str = "rated") -> str:
    """The profile of a base metric."""
    row = f"SELECT g.lang, g.stmt_id, g.n, g.gap, g.dir, coalesce(CAST(x.v AS DOUBLE), 0) AS v FROM {gap_rows} g LEFT JOIN"
    at = HELD.replace("theta", f"CAST({theta!r} AS DOUBLE)")
    if kind == "tf":
        return f"{name} AS MATERIALIZED ({row} (SELECT lang, n, gram, dir, count(*) AS v FROM {from_}{suffix} WHERE {at} GROUP BY ALL) x USING (lang, n, gram, dir))"
    if kind == "p":
        return f"{name} AS MATERIALIZED ({row} (SELECT lang, n, gram, cnt / max(cnt) OVER (PARTITION BY lang, n) AS v FROM grams{suffix}) x USING (lang, n, gram))"
    return f"{name} AS MATERIALIZED ({row} (SELECT lang, n, gram, dir, nbr, cnt / vcnt AS v FROM {from_}{suffix} WHERE {at}) x USING (lang, n, gram, dir, nbr) WHERE nbr IS NOT NULL)"


def offshoot(kind: str, source: str = "prof", more: str = "") -> str:
    """A query: source with the offshoot as v."""
    side = f"PARTITION BY lang, stmt_id, n, dir{more}"
    before, after = (f"coalesce({f}(v) OVER ({side} ORDER BY gap), v)" for f in ("lag", "lead"))
    v = {
        "raw": "v", "variance": f"v - sum(v) OVER ({side}) / count(v) OVER ({side})", "derivative": f"CASE WHEN dir = 'f' THEN v - {before} ELSE v - {after} END", "peak": f"(v - {before}) - ({after} - v)",
    }[kind]  # fmt: skip
    return f"SELECT lang, stmt_id, n, gap, dir{more}, {v} AS v FROM {source}"


def scaled(query: str, more: str = "") -> str:
    most = f"max(v) OVER (PARTITION BY lang, stmt_id, n, dir{more})"
    return f"SELECT * REPLACE (round(CASE WHEN {most} > 0 THEN v / {most} WHEN v IS NOT NULL THEN 0.0 END, 9) AS v) FROM ({query})"


def combined(query: str, combine: str = "max", more: str = "") -> str:
    score = {"max": "greatest(f, b)", "mean": "round((coalesce(f, b) + coalesce(b, f)) / 2, 9)", "forward": "f", "backward": "b"}[combine]
    return f"SELECT lang, stmt_id{more}, gap, {score} AS score FROM (SELECT lang, stmt_id{more}, gap, round(avg(v) FILTER (dir = 'f'), 9) AS f, round(avg(v) FILTER (dir = 'b'), 9) AS b FROM ({query}) GROUP BY ALL)"


def cut(breaks: str, stmts: str = "stmts") -> str:
    """A query: the tokens between the gaps of a query (lang, stmt_id, gap)."""
    return f"""SELECT lang, stmt_id, CAST(row_number() OVER (PARTITION BY lang, stmt_id ORDER BY a) AS INTEGER) AS tok_no, substr(text, a + 1, b - a) AS token FROM (
        SELECT lang, stmt_id, text, a, lead(a, 1, length(text)) OVER (PARTITION BY lang, stmt_id ORDER BY a) AS b FROM (
            SELECT lang, stmt_id, text, CAST(0 AS BIGINT) AS a FROM {stmts} WHERE length(text) > 0
            UNION ALL SELECT s.lang, s.stmt_id, s.text, x.gap FROM ({breaks}) x JOIN {stmts} s ON s.lang = x.lang AND s.stmt_id = x.stmt_id))"""


def tokens(c, prof: str = "prof", stmts: str = "stmts") -> str:
    """A query: the tokens of a configuration, from a profile of its base."""
    return cut(f"SELECT * FROM ({combined(scaled(offshoot(c.offshoot, prof)), c.combine)}) WHERE score > CAST({c.threshold!r} AS DOUBLE)", stmts)


def reference(stmts: str = "stmts") -> str:
    return f"""SELECT lang, stmt_id, CAST(unnest(range(1, len(t) + 1)) AS INTEGER) AS tok_no, unnest(t) AS token FROM (
        SELECT lang, stmt_id, regexp_extract_all(text, '[^\\s[:punct:]]+|[[:punct:]]') AS t FROM {stmts})"""


MI_GAPS = """SELECT g.lang, g.stmt_id, g.gap, m.mi FROM (SELECT lang, stmt_id, CAST(unnest(range(1, length(text))) AS INTEGER) AS gap, text FROM stmts) g
    LEFT JOIN (SELECT p.lang, p.gram AS pair, round(log2((p.cnt / p.s2) / ((x.cnt / x.s1) * (y.cnt / y.s1))), 9) AS mi
        FROM (SELECT *, sum(cnt) OVER (PARTITION BY lang) AS s2 FROM grams WHERE n = 2) p
        JOIN (SELECT *, sum(cnt) OVER (PARTITION BY lang) AS s1 FROM grams WHERE n = 1) x ON x.lang = p.lang AND x.gram = left(p.gram, 1)
        JOIN (SELECT *, sum(cnt) OVER (PARTITION BY lang) AS s1 FROM grams WHERE n = 1) y ON y.lang = p.lang AND y.gram = right(p.gram, 1)) m
    ON m.lang = g.lang AND m.pair = substr(g.text, g.gap, 2)"""
MI = f"SELECT lang, stmt_id, gap FROM ({MI_GAPS}) WHERE mi IS NULL OR mi < {w.MI_CUT}"
MARKS = " .,;:!?\"'()[]{}-"
LEXICON = f"""learned AS (SELECT lang, token AS word, count(*) AS freq FROM (
        SELECT lang, unnest(regexp_extract_all(line, '[^\\s[:punct:]]+|[[:punct:]]')) AS token FROM lines) GROUP BY ALL HAVING count(*) >= 2),
    lexicon AS (SELECT lang, word, max(freq) AS freq FROM (SELECT * FROM learned UNION ALL
        SELECT lang, substr('{MARKS.replace("'", "''")}', CAST(i AS INTEGER), 1), 1 FROM (SELECT DISTINCT lang FROM learned), range(1, {len(MARKS) + 1}) r(i)) GROUP BY ALL)"""


def greedy(by: str, lexicon: str = "lexicon", name: str = "lex", stmts: str = "stmts") -> tuple[list[str], str]:
    """Steps and the query of the greedy tokens. Which places begin a token is found by following 1, 2, 4 and so on tokens at once."""
    order = {"length": "length(word)", "frequency": "freq", "blend": "round(length(word) * ln(1 + freq), 9)"}[by]
    steps = [f"""{name}_best AS MATERIALIZED (SELECT lang, stmt_id, pos, word FROM (
            SELECT s.lang, s.stmt_id, s.pos, l.word, row_number() OVER (PARTITION BY s.lang, s.stmt_id, s.pos ORDER BY {order} DESC, length(word) DESC) AS k
            FROM (SELECT lang, stmt_id, pos, size, substr(text, pos, size) AS part FROM (SELECT lang, stmt_id, text, unnest(range(1, length(text) + 1)) AS pos FROM {stmts}),
                (SELECT DISTINCT length(word) AS size FROM {lexicon}) WHERE pos + size <= length(text) + 1) s
            JOIN {lexicon} l ON l.lang = s.lang AND l.word = s.part) WHERE k = 1)""",
        f"""{name}_next AS MATERIALIZED (SELECT s.lang, s.stmt_id, s.pos, coalesce(b.word, substr(s.text, s.pos, 1)) AS token
        FROM (SELECT lang, stmt_id, text, unnest(range(1, length(text) + 1)) AS pos FROM {stmts}) s LEFT JOIN {name}_best b ON b.lang = s.lang AND b.stmt_id = s.stmt_id AND b.pos = s.pos)""",
        f"{name}_j0 AS MATERIALIZED (SELECT lang, stmt_id, pos, pos + length(token) AS next FROM {name}_next)", f"{name}_r0 AS MATERIALIZED (SELECT lang, stmt_id, CAST(1 AS BIGINT) AS pos FROM {stmts} WHERE length(text) > 0)"]  # fmt: skip
    for k in range(17):
        on = "USING (lang, stmt_id, pos)"
        steps.append(f"{name}_r{k + 1} AS MATERIALIZED (SELECT * FROM {name}_r{k} UNION ALL SELECT lang, stmt_id, j.next FROM {name}_r{k} JOIN {name}_j{k} j {on})")
        steps.append(f"{name}_j{k + 1} AS MATERIALIZED (SELECT a.lang, a.stmt_id, a.pos, b.next FROM {name}_j{k} a JOIN {name}_j{k} b ON b.lang = a.lang AND b.stmt_id = a.stmt_id AND b.pos = a.next)")
    return steps, f"SELECT lang, stmt_id, CAST(row_number() OVER (PARTITION BY lang, stmt_id ORDER BY pos) AS INTEGER) AS tok_no, token FROM {name}_r17 JOIN {name}_next USING (lang, stmt_id, pos)"


def query(steps: list[str], last: str) -> str:
    return "WITH " + ",\n".join(steps) + "\n" + last


def f1(hyp: str, ref: str, by: str) -> str:
    """A query over hyp and ref with `by` and token."""
    return f"""SELECT {by}, matched, hyp, ref, round(CASE WHEN hyp > 0 THEN matched / hyp ELSE 0.0 END, 6) AS "precision", round(CASE WHEN ref > 0 THEN matched / ref ELSE 0.0 END, 6) AS recall,
        round(CASE WHEN hyp + ref > 0 THEN 2 * matched / (hyp + ref) ELSE 0.0 END, 6) AS f1 FROM (
        SELECT {by}, CAST(sum(least(coalesce(h, 0), coalesce(r, 0))) AS BIGINT) AS matched, CAST(sum(coalesce(h, 0)) AS BIGINT) AS hyp, CAST(sum(coalesce(r, 0)) AS BIGINT) AS ref
        FROM (SELECT {by}, token, count(*) AS h FROM ({hyp}) GROUP BY ALL) FULL OUTER JOIN (SELECT {by}, token, count(*) AS r FROM ({ref}) GROUP BY ALL) USING ({by}, token) GROUP BY ALL)"""


def solid(tokens_query: str) -> str:
    return f"SELECT * FROM ({tokens_query}) WHERE trim(token) <> ''"


def crossed(query_: str, name: str, values) -> str:
    return f"SELECT * FROM ({query_}), (VALUES {', '.join(f'({v!r})' for v in values)}) c({name})"


WHOLE, TRAIN = [DOCS, lines()], [TRAIN_DOCS, lines()]
TF1 = [*WHOLE, *model(2), BENCHMARK, gaps([1]), base("tf", 0.0)]
SPACED = [*TRAIN, *model(2), STATEMENTS, gaps([1]), base("tf", w.SPACED.theta)]


def _ways(query_: str, f: str, b: str, by: str = "stmt_id, gap") -> str:
    return f"(SELECT {by}, max(round(v, 9)) FILTER (dir = 'f') AS {f}, max(round(v, 9)) FILTER (dir = 'b') AS {b} FROM ({query_}) GROUP BY ALL)"


def _p_like(kind: str, n: int) -> str:
    steps = [*WHOLE, *model(n + 1), BENCHMARK, gaps([n]), base(kind, 0.0)]
    return query(steps, f"SELECT * FROM {_ways('SELECT * FROM prof', 'v_f', 'v_b')} JOIN {_ways(offshoot('variance'), 'dv_f', 'dv_b')} USING (stmt_id, gap) JOIN {_ways(offshoot('derivative'), 'd_f', 'd_b')} USING (stmt_id, gap)")


def _trivial(kind: str, stmts: str = "stmts") -> str:
    token = {"spaces": "unnest(string_split(text, ' '))", "symbols": "unnest(string_split(text, ''))", "line": "text"}[kind]
    return f"SELECT lang, stmt_id, 0 AS tok_no, {token} AS token FROM {stmts}"


def _together(made: dict[str, str], name: str = "method") -> str:
    return " UNION ALL ".join(f"SELECT lang, token, '{k}' AS {name} FROM ({solid(q)})" for k, q in made.items())


def _methods() -> tuple[list[str], dict[str, str]]:
    steps = [*TRAIN, *model(4), wide_edges([2]), rated("", "wide", "wide_rated"), STATEMENTS, gaps([1]), gaps([2], name="gaps2"), gaps([2], name="gaps_wide", wide=True), base("tf", w.SPACED.theta), base("p", 0.0, name="prof_p"), base("cp", 0.0, name="prof_cp"),
        base("tf", w.SPACED.theta, name="prof_tf_gram", gap_rows="gaps2", from_="wide_rated"), base("cp", 0.0, name="prof_cp_gram", gap_rows="gaps_wide", from_="wide_rated"), LEXICON]  # fmt: skip
    more, lex = greedy("length")
    made = {k: tokens(c, {"tf": "prof", "p": "prof_p", "cp": "prof_cp"}[c.base] if c.kind == "symbol" else f"prof_{c.base}_gram") for k, c in w.CONFIGS.items()}
    return [*steps, *more], made | {"mi": cut(MI), "lexicon": lex, **{k: _trivial(k) for k in ("spaces", "symbols", "line")}}


def _grid() -> list[str]:
    """Steps up to `scores`: the cells of the benchmark's grid."""
    from ..operators import compress, profile

    thetas, ths = levels(compress.LEVELS), ", ".join(f"(CAST({t!r} AS DOUBLE))" for t in w.LIMITS)
    found = f"""found AS MATERIALIZED (SELECT 'tf' AS base, lang, n, gram, dir, CAST(NULL AS VARCHAR) AS nbr, theta, CAST(count(*) AS DOUBLE) AS v FROM rated, {thetas} WHERE {HELD} GROUP BY ALL
        UNION ALL SELECT 'p', lang, n, gram, d.dir, NULL, theta, cnt / vmax FROM (SELECT *, max(cnt) OVER (PARTITION BY lang, n) AS vmax FROM grams WHERE n < 3), {thetas}, (VALUES ('f'), ('b')) d(dir) WHERE cnt >= theta * vmax
        UNION ALL SELECT 'cp', lang, n, gram, dir, nbr, theta, cnt / vcnt FROM rated, {thetas} WHERE {HELD})"""
    prof = f"""prof AS MATERIALIZED (SELECT g.base, g.lang, g.stmt_id, g.theta, g.n, g.gap, g.dir, coalesce(x.v, 0) AS v FROM (SELECT *, CASE WHEN base = 'cp' THEN nbr END AS across FROM gaps, (VALUES ('tf'), ('p'), ('cp')) b(base), {thetas}) g
        LEFT JOIN found x ON x.base = g.base AND x.lang = g.lang AND x.n = g.n AND x.gram = g.gram AND x.dir = g.dir AND x.theta = g.theta AND coalesce(x.nbr, '') = coalesce(g.across, ''))"""
    more = ", base, theta"
    each = " UNION ALL ".join(f"SELECT *, '{k}' AS offshoot FROM ({scaled(offshoot(k, 'prof', more), more)})" for k in profile.OFFSHOOTS)
    sets = ", ".join(f"('{'+'.join(map(str, s))}', {list(s)})" for s in w.SMALL_SETS)
    cells = f"cells AS MATERIALIZED ({combined(f'SELECT e.*, s.ranks FROM ({each}) e, (VALUES {sets}) s(ranks, members) WHERE list_contains(s.members, e.n)', 'max', ', base, theta, offshoot, ranks')})"
    cfg = "base, theta, offshoot, ranks, threshold"
    toks = f"""toks AS MATERIALIZED (SELECT lang, {cfg}, substr(text, CAST(a AS INTEGER) + 1, CAST(b - a AS INTEGER)) AS token, count(*) AS h FROM (
        SELECT lang, text, {cfg}, a, lead(a, 1, length(text)) OVER (PARTITION BY lang, stmt_id, {cfg} ORDER BY a) AS b FROM (
            SELECT DISTINCT s.lang, s.stmt_id, s.text, {cfg}, CAST(0 AS BIGINT) AS a FROM stmts s, (SELECT DISTINCT base, theta, offshoot, ranks FROM cells), (VALUES {ths}) t(threshold)
            UNION ALL SELECT s.lang, s.stmt_id, s.text, {cfg}, c.gap FROM cells c JOIN stmts s USING (lang, stmt_id), (VALUES {ths}) t(threshold) WHERE c.score > threshold)) GROUP BY ALL)"""
    ref = f"refs AS (SELECT lang, token, count(*) AS r FROM ({reference()}) GROUP BY ALL)"
    scores = f"""scores AS MATERIALIZED (SELECT lang, {cfg}, matched, hyp, ref, round(matched / hyp, 6) AS "precision", round(matched / ref, 6) AS recall, round(2 * matched / (hyp + ref), 6) AS f1 FROM (
        SELECT lang, {cfg}, CAST(sum(least(h, coalesce(r, 0))) AS BIGINT) AS matched, CAST(sum(h) AS BIGINT) AS hyp FROM toks LEFT JOIN refs USING (lang, token) WHERE trim(token) <> '' GROUP BY ALL)
        JOIN (SELECT lang, CAST(sum(r) AS BIGINT) AS ref FROM refs GROUP BY ALL) USING (lang))"""
    return [*TRAIN, *model(3), BENCHMARK, gaps([1, 2]), found, prof, cells, toks, ref, scores]


def _size(name: str, where: str) -> list[str]:
    return [lines(where, f"lines_{name}"), *model(2, f"_{name}", f"lines_{name}"), base("tf", w.SPACED.theta, f"_{name}", name=f"prof_{name}")]


def _sequence(seq: str, entity: str) -> str:
    steps = [f"stmts AS ({seq})", "lines AS (SELECT lang, text AS line FROM stmts)", *model(3), gaps([2]), base("tf", 0.0)]
    return query(steps, f"SELECT stmt_id AS {entity}, tok_no, token FROM ({tokens(w.EVENTS)})")


BARE_LINES = "lines AS (SELECT lang, replace(line, ' ', '') AS line FROM spaced WHERE replace(line, ' ', '') <> '')"


def _unspaced() -> tuple[list[str], dict[str, str], str]:
    """Steps, the tokens of each method, and the reference of text without blanks."""
    steps = [TRAIN_DOCS, lines("true", "spaced"), BARE_LINES, *model(3), STATEMENTS.replace("stmts AS", "spaced_stmts AS", 1), "stmts AS MATERIALIZED (SELECT lang, stmt_id, replace(text, ' ', '') AS text FROM spaced_stmts WHERE replace(text, ' ', '') <> '')",
        gaps([2]), base("tf", w.UNSPACED.theta), LEXICON.replace("FROM lines)", "FROM spaced)")]  # fmt: skip
    more, lex = greedy("length")
    made = {k: tokens(c) for k, c in w.UNSPACED_METHODS.items()}
    return [*steps, *more], made | {"lexicon": lex, "symbols": _trivial("symbols"), "line": _trivial("line")}, reference("spaced_stmts")


def _precision(toks: str, ref: str) -> tuple[list[str], str]:
    words = f"words AS (SELECT DISTINCT lang, word, 'learned' AS lexicon FROM lexicon UNION SELECT lang, word, 'corrected' FROM lexicon UNION SELECT lang, token, 'corrected' FROM ({ref}))"
    return [f"toks AS ({toks})", words], """SELECT *, round(known / total, 6) AS "precision" FROM (SELECT t.lang, t.method, x.lexicon, count(w.word) AS known, count(*) AS total FROM toks t CROSS JOIN (VALUES ('learned'), ('corrected')) x(lexicon)
        LEFT JOIN words w ON w.lang = t.lang AND w.word = t.token AND w.lexicon = x.lexicon GROUP BY ALL)"""


def _rules() -> str:
    """F1 of the other rules."""
    c = w.RULES
    steps = [*TRAIN, *model(4), wide_edges([2]), rated("", "wide", "wide_rated"), STATEMENTS, gaps([1]), gaps([2], name="gaps2"), gaps([2], name="gaps_wide", wide=True), base("tf", w.SPACED.theta), base("tf", w.SPACED.theta, name="prof2", gap_rows="gaps2"), base("cp", 0.0, name="prof_cp_gram", gap_rows="gaps_wide", from_="wide_rated"), LEXICON]
    more, lex = greedy("length")

    def peaks(source: str, kind: str, limit: float) -> str:
        side = "PARTITION BY lang, stmt_id, dir ORDER BY gap"
        low = "CAST('-infinity' AS DOUBLE)"
        return f"""SELECT DISTINCT lang, stmt_id, gap FROM (SELECT *, v > coalesce(lag(v) OVER ({side}), {low}) AND v >= coalesce(lead(v) OVER ({side}), {low}) AND v > {limit!r} AS top
            FROM ({scaled(offshoot(kind, source))})) WHERE top"""

    def over(query_: str, limit: float) -> str:
        return cut(f"SELECT * FROM ({combined(query_)}) WHERE score > CAST({limit!r} AS DOUBLE)")

    at = HELD.replace("theta", f"CAST({w.SPACED.theta!r} AS DOUBLE)")
    top = f"(SELECT lang, n, dir, max(v) AS top FROM (SELECT lang, n, gram, dir, count(*) AS v FROM rated WHERE {at} GROUP BY ALL) GROUP BY ALL)"
    # What is unseen at rank 2 is taken as at rank 1.
    seen2 = f"SELECT lang, n, gram, dir FROM rated WHERE n = 2 AND {at} GROUP BY ALL"
    backed = f"backed AS (SELECT g.lang, g.stmt_id, g.n, g.gap, g.dir, CASE WHEN s.gram IS NULL THEN o.v ELSE p.v END AS v FROM gaps2 g JOIN prof2 p USING (lang, stmt_id, n, gap, dir) LEFT JOIN ({seen2}) s ON s.lang = g.lang AND s.gram = g.gram AND s.dir = g.dir JOIN prof o ON o.lang = g.lang AND o.stmt_id = g.stmt_id AND o.gap = g.gap AND o.dir = g.dir)"
    mutual = """SELECT lang, stmt_id, gap FROM (SELECT *, coalesce(mi, CAST('-infinity' AS DOUBLE)) AS m, lag(coalesce(mi, CAST('-infinity' AS DOUBLE))) OVER s AS b, lead(coalesce(mi, CAST('-infinity' AS DOUBLE))) OVER s AS a FROM mis
        WINDOW s AS (PARTITION BY lang, stmt_id ORDER BY gap)) WHERE mi IS NULL OR m < coalesce(b, m) OR m < coalesce(a, m)"""
    lexed = f"lexed AS (SELECT *, sum(length(token)) OVER (PARTITION BY lang, stmt_id ORDER BY tok_no) AS b FROM ({lex}))"
    cuts = f"SELECT lang, stmt_id, gap FROM ({combined(scaled(offshoot('variance')))}) WHERE score > {w.SPACED.threshold!r}"
    hybrid = f"SELECT * FROM ({cuts}) c WHERE NOT EXISTS (SELECT 1 FROM lexed x WHERE x.lang = c.lang AND x.stmt_id = c.stmt_id AND c.gap < x.b AND c.gap > x.b - length(x.token))"
    made = {
        "tf_local_max": cut(peaks("prof", "derivative", c["tf_local_max"].threshold)), "cp_local_max": cut(peaks("prof_cp_gram", "derivative", c["cp_local_max"].threshold)),
        "tf_variance_model": over(f"SELECT * EXCLUDE (top) REPLACE (round(CASE WHEN top > 0 THEN v / top ELSE 0 END, 9) AS v) FROM ({offshoot('variance')}) JOIN {top} USING (lang, n, dir)", 0.4),
        "tf_variance_unscaled": over(f"SELECT * REPLACE (round(v, 9) AS v) FROM ({offshoot('variance')})", 5.0), "tf_backoff": over(scaled(offshoot("variance", "backed")), 0.4),
        "mi_mutual_best": cut(mutual), "hybrid": cut(hybrid),
    }  # fmt: skip
    return query([*steps, *more, backed, f"mis AS ({MI_GAPS})", lexed], f1(_together(made), crossed(reference(), "method", tuple(made)), "lang, method"))


PARAGRAPHS = r"""WITH bare AS (SELECT page_id, regexp_replace(html, '(?is)<script.*?</script\s*>|<style.*?</style\s*>|<!--.*?-->', '', 'g') AS h FROM pages),
    parts AS (SELECT page_id, unnest(string_split(h, '<')) AS part, unnest(range(len(string_split(h, '<')))) AS no FROM bare),
    known AS (SELECT page_id, no, lower(regexp_extract(part, '^(/?[A-Za-z][A-Za-z0-9]*)[\s>]', 1)) AS tag, CASE WHEN no = 0 THEN '' WHEN contains(part, '>') THEN substr(part, strpos(part, '>') + 1) ELSE '' END AS txt FROM parts),
    runs AS (SELECT *, count(*) FILTER (tag IN ('p', '/p', '/article', '/body', '/html', 'title', '/title', 'h1', 'h2', 'h3', 'h4', 'h5', 'h6', '/h1', '/h2', '/h3', '/h4', '/h5', '/h6')) OVER (PARTITION BY page_id ORDER BY no) AS run FROM known),
    pieces AS (SELECT page_id, run, first(tag ORDER BY no) AS tag, string_agg(txt, '' ORDER BY no) AS txt FROM runs GROUP BY page_id, run),
    said AS (SELECT page_id, CASE WHEN tag = 'p' THEN 'paragraph' WHEN tag = 'title' THEN 'title' ELSE 'heading' END AS kind, replace(replace(replace(replace(replace(txt, '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&#39;', chr(39)), '&amp;', '&') AS txt
        FROM pieces WHERE tag IN ('p', 'title', 'h1', 'h2', 'h3', 'h4', 'h5', 'h6'))
    SELECT page_id, kind, trim(regexp_replace(txt, '[ 	
]+', ' ', 'g')) AS line FROM said WHERE trim(regexp_replace(txt, '[ 	
]+', ' ', 'g')) <> ''"""


def _oracles() -> dict[str, str]:
    steps, methods = _methods()
    bare_steps, bare, bare_ref = _unspaced()
    sizes = ("small", "medium", "all", "good")
    out = {
        "w01_gram_counts": query([*WHOLE, grams(3)], "SELECT * FROM grams"),
        "w02_forward_edges": query([*WHOLE, grams(3), edges()], "SELECT lang, n, gram, nbr, cnt FROM edges WHERE dir = 'f'"),
        "w03_backward_edges": query([*WHOLE, grams(3), edges()], "SELECT lang, n, gram, nbr, cnt FROM edges WHERE dir = 'b'"),
        "w04_gram_gram_edges": query([*WHOLE, *(f"""w{n} AS (SELECT lang, substr(line, i, {n}) AS x, substr(line, i + {n}, {n}) AS y, count(*) AS cnt FROM (SELECT lang, line, unnest(range(1, length(line) - {2 * n} + 2)) AS i FROM lines) GROUP BY ALL)""" for n in (1, 2))],
            " UNION ALL ".join(f"SELECT lang, {n} AS n, 'f' AS dir, x AS gram, y AS nbr, cnt FROM w{n} UNION ALL SELECT lang, {n}, 'b', y, x, cnt FROM w{n}" for n in (1, 2))),
        "w05_freedom": query([*WHOLE, grams(3), edges()], "SELECT lang, n, gram, count(*) FILTER (dir = 'f') AS tf_f, count(*) FILTER (dir = 'b') AS tf_b FROM edges GROUP BY ALL"),
        "w06_probability": query([*WHOLE, grams(2)], "SELECT lang, n, gram, round(cnt / max(cnt) OVER (PARTITION BY lang, n), 9) AS p FROM grams"),
        "w07_conditional": query([*WHOLE, *model(3)], "SELECT lang, n, gram, dir, nbr, round(cnt / vcnt, 9) AS cp FROM rated"),
        "w08_compress_levels": query([*WHOLE, *model(3)], f"""SELECT lang, n, theta, part, params FROM (
            SELECT lang, n, theta, 'v' AS part, count(*) FILTER (cnt >= theta * vmax) AS params FROM (SELECT *, max(cnt) OVER (PARTITION BY lang, n) AS vmax FROM grams WHERE n < 3), {levels((0.0, 0.0001, 0.001, 0.01, 0.1))} GROUP BY ALL
            UNION ALL SELECT lang, n, theta, dir, count(*) FILTER ({HELD}) FROM rated, {levels((0.0, 0.0001, 0.001, 0.01, 0.1))} GROUP BY ALL)"""),
        "w09_blend_models": query([*WHOLE, grams(2)], "SELECT lang, n, count(*) AS grams, CAST(sum(cnt) AS BIGINT) AS total, CAST(0 AS BIGINT) AS differing FROM grams GROUP BY ALL"),
        "w10_profile_tf": query(TF1, f"SELECT * FROM {_ways('SELECT * FROM prof', 'tf_f', 'tf_b')} JOIN {_ways(offshoot('variance'), 'dvf', 'dvb')} USING (stmt_id, gap)"),
        "w11_profile_deriv_peak": query(TF1, f"SELECT * FROM {_ways(offshoot('derivative'), 'df_f', 'df_b')} JOIN {_ways(offshoot('peak'), 'peak_f', 'peak_b')} USING (stmt_id, gap)"),
        "w12_profile_p": _p_like("p", 1),
        "w13_profile_cp": _p_like("cp", 2),
        "w14_profile_ranks": query([*WHOLE, *model(4), BENCHMARK, gaps([1, 2, 3]), base("tf", 0.0)], f"SELECT * FROM {_ways(scaled(offshoot('variance')), 'dvf', 'dvb', 'n, stmt_id, gap')}"),
        "w15_tokens_tf_var": query([*WHOLE, *model(2), CORPUS, gaps([1]), base("tf", w.SPACED.theta)], tokens(w.SPACED)),
        "w16_tokens_tf_peak": query([CORPUS.replace("stmts AS", "spaced AS", 1), "stmts AS MATERIALIZED (SELECT lang, stmt_id, replace(text, ' ', '') AS text FROM spaced WHERE replace(text, ' ', '') <> '')", "lines AS (SELECT lang, text AS line FROM stmts)", *model(3), gaps([2]), base("tf", w.UNSPACED.theta)], tokens(w.UNSPACED)),
        "w17_tokens_mean_vs_max": query(SPACED, f1(_together({k: tokens(w.SPACED._replace(combine=k)) for k in w.COMBINES}, "combine"), crossed(reference(), "combine", w.COMBINES), "lang, combine")),
        "w18_mi_tokens": query([*WHOLE, grams(2), CORPUS], cut(MI)),
        "w22_reference_tokens": query([f"stmts AS ({ITEMS} UNION ALL {document_statements()})"], reference()),
        "w23_f1_by_method": query(steps, f1(_together(methods), crossed(reference(), "method", w.METHODS), "lang, method")),
        "w29_corpus_size": query([TRAIN_DOCS, STATEMENTS, gaps([1]), *_size("small", "doc_id % 10 = 1"), *_size("medium", "doc_id % 10 IN (1, 2, 3)"), *_size("all", "true"), *_size("good", "doc_id IN (SELECT doc_id FROM labels WHERE quality = 1)")],
            f1(_together({k: tokens(w.SPACED, f"prof_{k}") for k in sizes}, "size"), crossed(reference(), "size", sizes), "lang, size")),
        "w31_html_lines": PARAGRAPHS,
        "w32_events_segments": _sequence("SELECT 'seq' AS lang, user_id AS stmt_id, string_agg(left(event_type, 1), '' ORDER BY ts, event_id) AS text FROM events GROUP BY user_id", "user_id"),
        "w33_orders_segments": _sequence("SELECT 'seq' AS lang, o_custkey AS stmt_id, string_agg(left(o_orderstatus, 1), '' ORDER BY o_orderdate, o_orderkey) AS text FROM orders GROUP BY o_custkey", "o_custkey"),
        "w34_conversation_shift": query(["docs AS (SELECT 'en' AS lang, text FROM conversations)", lines(), *model(2), BENCHMARK, gaps([1]), base("tf", w.SPACED.theta)], f1(f"SELECT lang, token FROM ({solid(tokens(w.SPACED))})", f"SELECT lang, token FROM ({reference()})", "lang")),
        "w35_errors": query(SPACED, f"""SELECT lang, token, greatest(coalesce(r, 0) - coalesce(h, 0), 0) AS missed, greatest(coalesce(h, 0) - coalesce(r, 0), 0) AS invented
            FROM (SELECT lang, token, count(*) AS h FROM ({solid(tokens(w.SPACED))}) GROUP BY ALL) FULL OUTER JOIN (SELECT lang, token, count(*) AS r FROM ({reference()}) GROUP BY ALL) USING (lang, token)
            WHERE coalesce(r, 0) <> coalesce(h, 0)"""),
        "w36_grid_benchmark": query(_grid(), "SELECT * FROM scores"),
        "w37_unspaced_f1": query(bare_steps, f1(_together(bare), crossed(bare_ref, "method", tuple(bare)), "lang, method")),
        "w40_rules": _rules(),
        "w41_places": query(SPACED + [f"hyp AS MATERIALIZED (SELECT lang, stmt_id, a, a + length(token) AS b FROM (SELECT *, sum(length(token)) OVER (PARTITION BY lang, stmt_id ORDER BY tok_no) - length(token) AS a FROM ({tokens(w.SPACED)})) WHERE trim(token) <> '')",
            r"""every AS (SELECT lang, stmt_id, unnest(range(1, len(t) + 1)) AS tok_no, unnest(t) AS token FROM (SELECT lang, stmt_id, regexp_extract_all(text, '[^\s[:punct:]]+|[[:punct:]]|\s+') AS t FROM stmts))""",
            r"refs AS MATERIALIZED (SELECT lang, stmt_id, a, a + length(token) AS b FROM (SELECT *, sum(length(token)) OVER (PARTITION BY lang, stmt_id ORDER BY tok_no) - length(token) AS a FROM every) WHERE regexp_matches(token, '^\S'))",
            *(f"{t}_gaps AS (SELECT DISTINCT lang, stmt_id, unnest([CASE WHEN a > 0 THEN a END, b]) AS gap FROM {t})" for t in ("hyp", "refs"))],
            " UNION ALL ".join(f"""SELECT lang, matched, hyp, ref, round(matched / hyp, 6) AS "precision", round(matched / ref, 6) AS recall, round(2 * matched / (hyp + ref), 6) AS f1, '{of}' AS of FROM (
                SELECT lang, count(*) FILTER (h AND r) AS matched, count(*) FILTER (h) AS hyp, count(*) FILTER (r) AS ref FROM (SELECT lang, coalesce(x.h, false) AS h, coalesce(y.r, false) AS r
                FROM (SELECT *, true AS h FROM hyp{g} WHERE {cond}) x FULL OUTER JOIN (SELECT *, true AS r FROM refs{g} WHERE {cond}) y USING (lang, stmt_id, {key})) GROUP BY lang)""" for of, g, key, cond in (("spans", "", "a, b", "true"), ("breaks", "_gaps", "gap", "gap IS NOT NULL")))),
        "w43_model_cost": query([*WHOLE, grams(3)], "SELECT lang, n, count(*) AS grams, CAST(sum(strlen(gram) + 8) AS BIGINT) AS bytes FROM grams GROUP BY ALL"),
        "w44_degrees": query([*WHOLE, grams(3), edges()], """SELECT lang, n, out_degree, in_degree, count(*) AS vertices FROM (SELECT g.lang, g.n, g.gram, count(e.nbr) FILTER (e.dir = 'f') AS out_degree, count(e.nbr) FILTER (e.dir = 'b') AS in_degree
            FROM (SELECT * FROM grams WHERE n < 3) g LEFT JOIN edges e ON e.lang = g.lang AND e.n = g.n AND e.gram = g.gram GROUP BY ALL) GROUP BY ALL"""),
        "w45_unsupervised_threshold": query([*_grid(), """steps AS (SELECT *, abs(ln(hyp) - ln(lag(hyp) OVER (PARTITION BY lang, base, offshoot, ranks, theta ORDER BY threshold))) AS change FROM scores)"""],
            "SELECT lang, base, offshoot, ranks, theta, threshold, hyp, f1 FROM (SELECT *, row_number() OVER (PARTITION BY lang, base, offshoot, ranks, theta ORDER BY change ASC NULLS LAST, threshold) AS k FROM steps) WHERE k = 1"),
    }  # fmt: skip
    more, lex = greedy("length")
    with_lexicon = [*SPACED, LEXICON, *more]
    made, last = _precision(_together({"tf_variance": tokens(w.SPACED), "lexicon": lex, "reference": reference()}), reference())
    out["w24_lexicon_precision"] = query([*with_lexicon, *made], last)
    made, last = _precision(_together({**{k: bare[k] for k in (*w.UNSPACED_METHODS, "lexicon")}, "reference": bare_ref}), bare_ref)
    out["w38_unspaced_precision"] = query([*bare_steps, *made], last)
    for key, by in (("w19_lexicon_length", "length"), ("w20_lexicon_freq", "frequency"), ("w21_lexicon_blend", "blend")):
        more, last = greedy(by)
        out[key] = query([*TRAIN, STATEMENTS, LEXICON, *more], last)
    steps, hyps = [*TRAIN, STATEMENTS, LEXICON], {}
    for percent in w.MISSING:
        steps.append(f"lexicon_{percent} AS (SELECT * FROM lexicon WHERE left(md5(word), 2) >= '{round(256 * percent / 100):02x}')")
        more, hyps[percent] = greedy("length", f"lexicon_{percent}", f"lex_{percent}")
        steps += more
    hyp = " UNION ALL ".join(f"SELECT lang, token, {k} AS percent FROM ({solid(q)})" for k, q in hyps.items())
    out["w30_missing_words"] = query(steps, f1(hyp, crossed(reference(), "percent", w.MISSING), "lang, percent"))
    out["w39_summary"] = _summary_sql(out)
    return out


def _summary_sql(made: dict[str, str]) -> str:
    """The summary from the queries that it sums up."""
    fixed = "lexicon = 'corrected'"
    return f"""WITH spaced AS (SELECT lang, CASE method WHEN 'tf_variance' THEN 'freedom' ELSE method END AS method, f1 FROM ({made['w23_f1_by_method']}) WHERE method IN ('tf_variance', 'lexicon')),
        bare AS (SELECT lang, CASE method WHEN 'tf_peak' THEN 'freedom' ELSE method END AS method, f1 FROM ({made['w37_unspaced_f1']}) WHERE method IN ('tf_peak', 'lexicon')),
        right_ AS (SELECT lang, CASE method WHEN 'tf_variance' THEN 'freedom' ELSE method END AS method, "precision" FROM ({made['w24_lexicon_precision']}) WHERE {fixed}),
        bare_right AS (SELECT lang, CASE method WHEN 'tf_peak' THEN 'freedom' ELSE method END AS method, "precision" FROM ({made['w38_unspaced_precision']}) WHERE {fixed})
        SELECT s.lang, s.method, f1, p."precision", r."precision" AS reference FROM spaced s JOIN right_ p USING (lang, method) JOIN (SELECT * FROM right_ WHERE method = 'reference') r ON r.lang = s.lang
        UNION ALL SELECT s.lang || ' unspaced', s.method, f1, p."precision", r."precision" FROM bare s JOIN bare_right p USING (lang, method) JOIN (SELECT * FROM bare_right WHERE method = 'reference') r ON r.lang = s.lang"""


ORACLES = _oracles()
