"""Parts of the SQL twins: common table expressions that stand for the Spark stages."""

from __future__ import annotations

from phasewarp.sources.stopwords import LANGUAGES, all_stop_words, stop_list
from phasewarp.sources.tables import PAIR_SCENARIO, PROFILES, SCENARIO, profile_intervals


def quoted(words) -> str:
    return ", ".join("'" + w.replace("'", "''") + "'" for w in words)


def r(x: str, digits: int = 6) -> str:
    """Rounded, without negative zero."""
    return f"(round({x}, {digits}) + 0.0)"


def with_(*parts: str) -> str:
    return "WITH RECURSIVE " + ",\n".join(parts) + "\n"


PROFILE_ROWS = "prof(profile, day, s, e) AS (VALUES " + ", ".join(f"('{p}', {d}, {s}, {e})" for p in PROFILES for d, s, e in profile_intervals(p)) + ")"
RECORDS = """rec AS (
  SELECT CAST(CAST(substr(source, 4) AS INT) % 9 AS VARCHAR) AS event, CASE WHEN doc_id % 2 = 0 THEN 'A' ELSE 'B' END AS medium,
         doc_id AS record_id, text, lang
  FROM documents WHERE lang = 'en')"""
PAIR_RECORDS = r"""rec AS (
  SELECT lang AS event, 'A' AS medium, doc_id AS record_id, text, lang FROM documents WHERE lang IN ('en', 'fr', 'de', 'es')
  UNION ALL
  SELECT l, 'B', page_id, %s, l FROM (SELECT *, regexp_extract(url, '^[a-z]+://[^/]+/([a-z]{2})/', 1) AS l FROM pages) WHERE l IN ('en', 'fr', 'de', 'es'))"""


def html_text(x: str) -> str:
    for pattern in (r"(?is)<script\b.*?</script\s*>", r"(?is)<style\b.*?</style\s*>", r"(?s)<!--.*?-->", r"(?s)<[^>]*>"):
        x = f"regexp_replace({x}, '{pattern}', ' ', 'g')"
    for name, char in (("&nbsp;", " "), ("&lt;", "<"), ("&gt;", ">"), ("&quot;", '"'), ("&#39;", "''"), ("&amp;", "&")):
        x = f"replace({x}, '{name}', '{char}')"
    return x


def clocked(scenario: dict = SCENARIO, clock: str = "quota", records: str = RECORDS) -> list[str]:
    """rec, prof, scen, timed: records with their phase."""
    scen = "scen(event, pa, pb, lag) AS (VALUES " + ", ".join(f"('{e}', '{a}', '{b}', {lag})" for e, (a, b, lag) in scenario.items()) + ")"
    key = "md5(CAST(record_id AS VARCHAR))"
    if clock == "hash":
        u = f"CAST(('0x' || substr({key}, 1, 8)) AS BIGINT) % 1000"
    else:
        u = f"((2 * row_number() OVER (PARTITION BY event, medium ORDER BY {key}, record_id) - 1) * 1000) // (2 * count(*) OVER (PARTITION BY event, medium))"
    return [
        records, PROFILE_ROWS, scen, f"slot AS (SELECT *, {u} AS u FROM rec)",
        """timed AS (
  SELECT slot.*, CASE WHEN medium = 'A' THEN day ELSE least(30, day + lag) END AS phase
  FROM slot JOIN scen USING (event) JOIN prof ON profile = CASE WHEN medium = 'A' THEN pa ELSE pb END AND u >= s AND u < e)""",
    ]


def tokens(stop: str = "lang") -> list[str]:
    """tok and pw: words after stop lists, and their counts per phase."""
    if stop == "all":
        listed = f"word NOT IN ({quoted(all_stop_words())})"
    else:
        listed = "NOT (" + " OR ".join(f"(lang = '{c}' AND word IN ({quoted(stop_list(c))}))" for c in LANGUAGES) + ")"
    return [
        rf"raw AS (SELECT event, medium, phase, record_id, lang, unnest(regexp_extract_all(lower(text), '[\p{{L}}\p{{N}}]+')) AS word FROM timed)",
        f"tok AS (SELECT event, medium, phase, record_id, word FROM raw WHERE length(word) >= 2 AND {listed})",
        "pw AS (SELECT event, medium, phase, word, count(*) AS freq, count(DISTINCT record_id) AS rec_freq FROM tok GROUP BY ALL)",
    ]


def series(source: str, n: int = 30, name: str = "epts") -> list[str]:
    """A dense, normalised series from ``source(event, medium, phase, pop)``."""
    return [
        f"{name}_g AS (SELECT event, medium, unnest(range(1, {n} + 1)) AS phase FROM (SELECT DISTINCT event, medium FROM {source}))",
        f"{name}_d AS (SELECT g.event, g.medium, CAST(g.phase AS INT) AS phase, coalesce(CAST(x.pop AS DOUBLE), 0.0::DOUBLE) AS pop FROM {name}_g g LEFT JOIN {source} x USING (event, medium, phase))",
        f"{name} AS (SELECT *, coalesce(pop / nullif(sum(pop) OVER (PARTITION BY event, medium), 0), 0.0::DOUBLE) AS pop_norm FROM {name}_d)",
    ]


def fitted(scope: str = "event, medium", words: str = "pw", fixed: float | None = None, support: str = "auto", cut: str = "auto") -> list[str]:
    """voc, fit, cutoff, kept."""
    infinite = "CASE WHEN alpha > 1 THEN pow(2.0::DOUBLE, 1 / (alpha - 1)) END"
    short = "CASE WHEN abs(alpha - 1) < 1e-12 THEN sqrt(vocab_size) ELSE pow((1 + pow(CAST(vocab_size AS DOUBLE), 1 - alpha)) / 2, 1 / (1 - alpha)) END"
    use = {"auto": f"coalesce({infinite} <= vocab_size, FALSE)", "infinite": "TRUE", "truncated": "FALSE"}[support]
    th = f"{float(fixed)}::DOUBLE" if fixed is not None else "h * pow(r_half, -alpha)"
    regime = "'fixed'" if fixed is not None else "regime"
    on = " AND ".join(f"v.{c.strip()} = c.{c.strip()}" for c in scope.split(","))
    passes = {"auto": "CASE WHEN enough THEN freq >= th * (1 - 1e-9) ELSE rank <= greatest(r_half, 2) END", "frequency": "freq >= th * (1 - 1e-9)", "rank": "rank <= greatest(r_half, 2)"}[cut]
    return [
        f"voc AS (SELECT *, row_number() OVER (PARTITION BY {scope} ORDER BY freq DESC, word) AS rank FROM (SELECT {scope}, word, CAST(sum(freq) AS BIGINT) AS freq FROM {words} GROUP BY ALL))",
        f"fit0 AS (SELECT {scope}, -regr_slope(ln(freq), ln(rank)) AS alpha, exp(regr_intercept(ln(freq), ln(rank))) AS h, count(*) AS vocab_size FROM voc GROUP BY ALL)",
        f"fit1 AS (SELECT *, CASE WHEN {use} THEN {infinite} ELSE {short} END AS r_half, CASE WHEN {use} THEN 'infinite' ELSE 'truncated' END AS regime FROM fit0)",
        f"cutoff AS (SELECT * REPLACE ({regime} AS regime), {th} AS th FROM fit1)",
        f"joined AS (SELECT v.*, c.th, c.r_half, c.regime, sum(CASE WHEN v.freq >= c.th * (1 - 1e-9) AND v.rank <= 2 THEN 1 ELSE 0 END) OVER (PARTITION BY {', '.join('v.' + c.strip() for c in scope.split(','))}) >= 2 AS enough FROM voc v JOIN cutoff c ON {on})",
        f"kept AS (SELECT {scope}, word, freq, rank FROM joined WHERE {passes})",
    ]


LEFT = "lw AS (SELECT pw.* FROM pw SEMI JOIN kept USING (event, medium, word))"
VECTORS = [
    "ew AS (SELECT event, word, row_number() OVER (PARTITION BY event ORDER BY sum(freq) DESC, word) AS r FROM pw GROUP BY event, word)",
    "nv AS (SELECT count(*) AS n FROM embeddings)",
    """vec AS (SELECT ew.event, ew.word, CAST(a.embedding AS DOUBLE[]) AS vr, CAST(b.embedding AS DOUBLE[]) AS vd
  FROM ew CROSS JOIN nv LEFT JOIN embeddings a ON a.vec_id = (r - 1) % n LEFT JOIN embeddings b ON b.vec_id = (r - 1 + 37) % n)""",
]


def chars_dot(a: str, b: str) -> str:
    count = lambda w, c: f"(length({w}) - length(replace({w}, {c}, '')))"
    return f"CAST(list_sum(list_transform(list_distinct(string_split({a}, '')), lambda c: {count(a, 'c')} * {count(b, 'c')})) AS DOUBLE)"


def lexical(a: str, b: str) -> str:
    return f"coalesce({chars_dot(a, b)} / nullif(sqrt({chars_dot(a, a)}) * sqrt({chars_dot(b, b)}), 0), 0.0::DOUBLE)"


def edges(beta: float = 0.7, gamma: float = 0.02, positive: bool = True) -> list[str]:
    cos = lambda v: f"coalesce(list_dot_product(a.{v}, b.{v}) / nullif(sqrt(list_dot_product(a.{v}, a.{v})) * sqrt(list_dot_product(b.{v}, b.{v})), 0), 0.0::DOUBLE)"
    return [
        LEFT, *VECTORS,
        "kw AS (SELECT DISTINCT event, medium, word FROM lw)",
        "kv AS (SELECT kw.*, vr, vd FROM kw LEFT JOIN vec USING (event, word))",
        f"""pairs AS (SELECT a.event, a.medium, a.word AS w1, b.word AS w2,
    {beta} * {cos('vr')} + {1 - beta} * {cos('vd')} AS sem,
    {lexical('a.word', 'b.word')} AS str
  FROM kv a JOIN kv b ON a.event = b.event AND a.medium = b.medium AND a.word < b.word)""",
        f"edges AS (SELECT * FROM (SELECT *, {gamma} * sem + {1 - gamma} * str AS sim FROM pairs)" + (" WHERE sim > 0)" if positive else ")"),
        """graph AS (SELECT e.event, e.medium, x.phase, w1, w2, sim FROM edges e
  JOIN lw x ON x.event = e.event AND x.medium = e.medium AND x.word = e.w1
  JOIN lw y ON y.event = e.event AND y.medium = e.medium AND y.word = e.w2 AND y.phase = x.phase)""",
        "contrib AS (SELECT event, medium, phase, w1 AS word FROM graph UNION SELECT event, medium, phase, w2 FROM graph)",
    ]


def ranks(rounds: int = 30, theta: float = 0.85, teleport: str = "phase") -> list[str]:
    base = "n" if teleport == "phase" else "ne"
    return [
        "both_ways AS (SELECT event, medium, phase, w1 AS i, w2 AS j, sim FROM graph UNION ALL SELECT event, medium, phase, w2, w1, sim FROM graph)",
        "share AS (SELECT *, sim / sum(sim) OVER (PARTITION BY event, medium, phase, j) AS p FROM both_ways)",
        """nodes AS (SELECT c.*, CAST(count(*) OVER (PARTITION BY event, medium, phase) AS DOUBLE) AS n, CAST(u.ne AS DOUBLE) AS ne
  FROM contrib c JOIN (SELECT event, medium, count(DISTINCT word) AS ne FROM contrib GROUP BY ALL) u USING (event, medium))""",
        f"""walk AS (SELECT event, medium, phase, word, {base} AS base, 1 / n AS tr, 0 AS k FROM nodes
  UNION ALL
  SELECT w.event, w.medium, w.phase, s.i, any_value(w.base), {1 - theta} / any_value(w.base) + {theta} * sum(s.p * w.tr), any_value(w.k) + 1
  FROM walk w JOIN share s ON s.event = w.event AND s.medium = w.medium AND s.phase = w.phase AND s.j = w.word
  WHERE w.k < {rounds} GROUP BY w.event, w.medium, w.phase, s.i)""",
        f"tr AS (SELECT event, medium, phase, word, tr FROM walk WHERE k = {rounds})",
    ]


def swp(total: str = "kept", compensation: str = "printed") -> list[str]:
    op = "/" if compensation == "printed" else "*"
    return [
        f"tot AS (SELECT event, medium, phase, sum(freq) AS total FROM {'lw' if total == 'kept' else 'pw'} GROUP BY ALL)",
        f"wt AS (SELECT tr.*, tr {op} count(*) OVER (PARTITION BY event, medium, phase) * total AS weight FROM tr JOIN tot USING (event, medium, phase))",
        "wp AS (SELECT lw.event, lw.medium, lw.phase, lw.word, freq, coalesce(weight, 0.0::DOUBLE) AS weight, freq * coalesce(weight, 0.0::DOUBLE) AS pop FROM lw LEFT JOIN wt USING (event, medium, phase, word))",
        "pp AS (SELECT event, medium, phase, sum(pop) AS pop FROM wp GROUP BY ALL)",
    ]


def slopes(source: str = "epts") -> list[str]:
    w = "(PARTITION BY event, medium ORDER BY phase)"
    return [
        f"sl0 AS (SELECT *, (pop_norm - lag(pop_norm) OVER {w} + (lead(pop_norm) OVER {w} - lag(pop_norm) OVER {w}) / 2) / 2 AS s0 FROM (SELECT * REPLACE (round(pop_norm, 12) AS pop_norm) FROM {source}))",
        f"sl AS (SELECT event, medium, phase, pop_norm, coalesce(s0, lead(s0) OVER {w}, lag(s0) OVER {w}, 0.0::DOUBLE) AS slope FROM sl0)",
    ]


def signatures(s: int = 64, seed: int = 42) -> list[str]:
    digest = f"md5('{seed}:' || word || ':' || CAST(l AS VARCHAR))"
    num = lambda at: f"(CAST(('0x' || substr({digest}, {at}, 8)) AS BIGINT) + 1) / 4294967297.0::DOUBLE"
    return [
        f"sg AS (SELECT event, medium, phase, l, sum(sqrt(-2 * ln({num(1)})) * cos(2 * pi() * {num(9)})) >= 0 AS up FROM contrib CROSS JOIN (SELECT unnest(range(0, {s})) AS l) GROUP BY ALL)",
        # phases without contributive words have all signs up
        f"""sv AS (SELECT e.event, e.medium, e.phase, coalesce(x.v, list_transform(range(0, {s}), lambda q: 1)) AS v FROM epts e
  LEFT JOIN (SELECT event, medium, phase, list(CASE WHEN up THEN 1 ELSE 0 END ORDER BY l) AS v FROM sg GROUP BY ALL) x USING (event, medium, phase))""",
    ]


def cells(methods: list[tuple[str, str]], vocab: bool = True, s: int = 64) -> list[str]:
    """cell(event, method, i, j, d) from (name, expression over l, g, v, off)."""
    v = f"2.0::DOUBLE * list_sum(list_transform(list_zip(va.v, vb.v), lambda z: abs(z[1] - z[2]))) / {float(s)}" if vocab else "1.0::DOUBLE"
    sides = "LEFT JOIN sv va ON va.event = a.event AND va.medium = 'A' AND va.phase = a.phase LEFT JOIN sv vb ON vb.event = b.event AND vb.medium = 'B' AND vb.phase = b.phase" if vocab else ""
    grid = f"""grid AS (SELECT a.event, a.phase AS i, b.phase AS j, abs(a.pop_norm - b.pop_norm) AS l, abs(a.slope - b.slope) AS g, {v} AS v, CAST(abs(a.phase - b.phase) AS DOUBLE) AS off
  FROM sl a JOIN sl b ON a.event = b.event AND a.medium = 'A' AND b.medium = 'B' {sides})"""
    return [grid, "cell AS (" + " UNION ALL ".join(f"SELECT event, '{n}' AS method, i, j, {e} AS d FROM grid" for n, e in methods) + ")"]


def omega(eta: float, tau: float) -> str:
    return f"1 / (1 + exp(least(700.0::DOUBLE, -{float(eta)} * (off - {float(tau)}))))"


COMPOUND = "sqrt(greatest(v * l * g, 0))"
#: Expressions of the ten methods and their predecessor factors.
EXPRESSIONS = {
    "dtw": "l", "ddtw": "g", "dtw_bias": "l", "ddtw_bias": "g", "wdtw": f"l + {omega(10, 2)}", "wddtw": f"g + {omega(5, 3.2)}",
    "cw": COMPOUND, "wcw_1": f"{COMPOUND} + {omega(5, 3.2)}", "wcw": f"{COMPOUND} + {omega(10, 2)}", "wcw_3": f"{COMPOUND} + {omega(5, 2.2)}",
}
PLAIN = [m for m in EXPRESSIONS if not m.endswith("bias")]


def warped(bias: bool = True, third: str = "cumulated", rule: str = "cumulated") -> list[str]:
    """cum (cumulated rows), costs (whole matrices) and match (paths) by recursion over rows."""
    up, diag, left = ("CASE WHEN method LIKE '%bias%' THEN 1.2 ELSE 1.0 END", "1.0", "CASE WHEN method LIKE '%bias%' THEN 1.2 ELSE 1.0 END") if bias else ("1.0", "1.0", "1.0")
    before = "acc[len(acc)]" if third == "cumulated" else "x[5]"
    return [
        "drow AS (SELECT event, method, i, list(d ORDER BY j) AS d FROM cell GROUP BY ALL)",
        f"""cum AS (
  SELECT event, method, i, d, list_transform(range(1, len(d) + 1), lambda k: list_sum(d[1:k])) AS g FROM drow WHERE i = 1
  UNION ALL
  SELECT n.event, n.method, n.i, n.d,
    list_reduce(list_transform(range(2, len(n.d) + 1), lambda k: [n.d[k], {up.replace('method', 'n.method')} * p.g[k], {diag} * p.g[k - 1], {left.replace('method', 'n.method')}, n.d[k - 1]]),
                lambda acc, x: list_append(acc, x[1] + least(x[2], x[3], x[4] * {before})), [n.d[1] + p.g[1]])
  FROM cum p JOIN drow n ON n.event = p.event AND n.method = p.method AND n.i = p.i + 1)""",
        "costs AS (SELECT event, method, list(g ORDER BY i) AS g, list(d ORDER BY i) AS d, count(*) AS n, any_value(len(d)) AS m FROM cum GROUP BY ALL)",
        f"""back AS (
  SELECT event, method, CAST(n AS INT) AS i, CAST(m AS INT) AS j, 0 AS b FROM costs
  UNION ALL
  SELECT event, method, CAST(CASE WHEN i = 1 THEN i WHEN j = 1 THEN i - 1 WHEN dg <= up OR dg <= lf THEN CASE WHEN dg <= up AND dg <= lf THEN i - 1 WHEN up <= lf THEN i - 1 ELSE i END WHEN up <= lf THEN i - 1 ELSE i END AS INT),
         CAST(CASE WHEN i = 1 THEN j - 1 WHEN j = 1 THEN j WHEN dg <= up AND dg <= lf THEN j - 1 WHEN up <= lf THEN j ELSE j - 1 END AS INT), b + 1
  FROM (SELECT b.*, c.{'g' if rule == 'cumulated' else 'd'}[b.i - 1][b.j - 1] AS dg, c.{'g' if rule == 'cumulated' else 'd'}[b.i - 1][b.j] AS up, c.{'g' if rule == 'cumulated' else 'd'}[b.i][b.j - 1] AS lf
        FROM back b JOIN costs c USING (event, method) WHERE b.i > 1 OR b.j > 1))""",
        "match AS (SELECT event, method, CAST(max(b) OVER (PARTITION BY event, method) - b + 1 AS INT) AS k, i, j FROM back)",
    ]


def base(scenario: dict = SCENARIO, clock: str = "quota", stop: str = "lang") -> list[str]:
    return [*clocked(scenario, clock), *tokens(stop)]


def full_swp(scenario: dict = SCENARIO, clock: str = "quota", fixed: float | None = 10.0, **kw) -> list[str]:
    return [*base(scenario, clock), *fitted(fixed=fixed), *edges(), *ranks(), *swp(**kw), *seen_series("pp")]


def seen_series(source: str, n: int = 30) -> list[str]:
    """As :func:`series`, with the grid from all phase words."""
    parts = series(source, n)
    return [parts[0].replace(f"FROM {source}", "FROM pw"), *parts[1:]]


PAIRS = clocked(PAIR_SCENARIO, "quota", PAIR_RECORDS % html_text("html"))
