"""DuckDB SQL with the same rows as the queries, built from the same constants (names, variants, word lists)."""

from __future__ import annotations

from propalign.baselines import lsh, semgraph
from propalign.functions.formats import CHAR_NAMES, CHAR_TYPES, EXPONENT, FINITE, LARGEST, NUMBER, TOKEN_TYPES
from propalign.functions import strings
from propalign.functions.lexicon import EPSILON, word_concepts
from propalign.plans.experiments import ruled_network
from propalign.plans.splits import FRACTIONS
from propalign.plans.stats import SAMPLE
from propalign.sources.domains import DOMAINS, alignment, instances_sql, source_name

ALL = tuple(DOMAINS)
P = "cls, source, prop"
PAIR = "cls, source_a, prop_a, source_b, prop_b"


def values(rows: list[tuple], columns: str) -> str:
    told = lambda v: "NULL" if v is None else str(v).lower() if isinstance(v, bool) else str(v) if isinstance(v, (int, float)) else "'" + str(v).replace("'", "''") + "'"
    return f"(SELECT * FROM (VALUES {', '.join('(' + ', '.join(map(told, r)) + ')' for r in rows)}) v({columns}))"


def inst(domains: tuple[str, ...] = ALL) -> str:
    return "(" + " UNION ALL ".join(f"SELECT * FROM ({instances_sql(c)})" for c in domains) + ")"


def props(domains: tuple[str, ...] = ALL) -> str:
    return f"(SELECT DISTINCT {P} FROM {inst(domains)})"


def align(domains: tuple[str, ...] = ALL) -> str:
    return values([r for c in domains for r in alignment(DOMAINS[c])], "cls, source, prop, ref_prop")


def paired(relation: str, extra: tuple[str, ...] = ()) -> str:
    """Unordered pairs of a relation's rows (cls, source, prop, extra)."""
    cols = "".join(f", a.{c} AS {c}_a, b.{c} AS {c}_b" for c in extra)
    return f"(SELECT a.cls, a.source AS source_a, a.prop AS prop_a, b.source AS source_b, b.prop AS prop_b{cols} FROM {relation} a JOIN {relation} b ON a.cls = b.cls AND a.source < b.source)"


def truth(domains: tuple[str, ...] = ALL) -> str:
    return f"(SELECT DISTINCT a.cls, a.source AS source_a, a.prop AS prop_a, b.source AS source_b, b.prop AS prop_b FROM {align(domains)} a JOIN {align(domains)} b ON a.cls = b.cls AND a.ref_prop = b.ref_prop AND a.source < b.source)"


def labelled(relation: str, domains: tuple[str, ...]) -> str:
    return f"(SELECT x.*, CASE WHEN t.cls IS NULL THEN 0 ELSE 1 END AS label FROM {relation} x LEFT JOIN {truth(domains)} t USING ({PAIR}))"


def words(c: str) -> str:
    return f"list_filter(regexp_split_to_array(lower({c}), '[^\\p{{L}}\\p{{N}}]+'), lambda w: w <> '')"


def normal(c: str) -> str:
    return f"trim(regexp_replace(lower({c}), '[^\\p{{L}}\\p{{N}}]+', ' ', 'g'))"


# --- features

_COUNT = {n: f"length(regexp_replace(value, '[^{p[1:-1] if p.startswith('[') else p}]', '', 'g'))" for n, p in CHAR_TYPES.items()}
_COUNT["other"] = f"length(value) - ({' + '.join(_COUNT[n] for n in ('letter', 'mark', 'number', 'punctuation', 'symbol', 'white'))})"
_TOKENS = "list_filter(regexp_split_to_array(value, '[\\p{Z}\\s]+'), lambda t: t <> '')"
_TOKEN = {n: f"len(list_filter(tokens, lambda t: regexp_matches(t, '{p}')))" for n, p in TOKEN_TYPES.items()}
_NUM = f"CASE WHEN regexp_matches(trim(value, ' '), '{NUMBER}') AND abs(TRY_CAST(trim(value, ' ') AS DOUBLE)) <= CASE WHEN regexp_matches(value, '{EXPONENT}') THEN {LARGEST} ELSE {FINITE} END THEN TRY_CAST(trim(value, ' ') AS DOUBLE) ELSE -1.0 END"


def meta_rows(relation: str) -> str:
    """Instances with the 28 features m0 to m27 and num."""
    counts = ", ".join(f"CAST({_COUNT[n]} AS DOUBLE) AS c{i}" for i, n in enumerate(CHAR_NAMES))
    toks = ", ".join(f"CAST({_TOKEN[n]} AS DOUBLE) AS t{i}" for i, n in enumerate(TOKEN_TYPES))
    share = lambda a, b: f"CASE WHEN {b} > 0 THEN {a} / {b} ELSE 0.0 END"
    cols, k = [], 0
    for i in range(len(CHAR_NAMES)):
        cols += [f"c{i} AS m{k}", f"{share(f'c{i}', 'size')} AS m{k + 1}"]
        k += 2
    for i in range(len(TOKEN_TYPES)):
        cols += [f"t{i} AS m{k}", f"{share(f't{i}', 'n_tokens')} AS m{k + 1}"]
        k += 2
    return f"(SELECT *, {', '.join(cols)} FROM (SELECT *, {toks}, len(tokens) AS n_tokens FROM (SELECT *, {counts}, length(value) AS size, {_NUM} AS num, {_TOKENS} AS tokens FROM {relation})))"


def profile(relation: str, agg: str = "avg", digits: int | None = 4) -> str:
    r = (lambda x: f"round({x}, {digits})") if digits is not None else (lambda x: x)
    return f"SELECT {P}, count(*) AS n_instances, {', '.join(f'{r(f"{agg}(m{i})")} AS m{i}' for i in range(28))}, {r(f'{agg}(num)')} AS num FROM {meta_rows(relation)} GROUP BY {P}"


_VALUES_SQL = f"(SELECT DISTINCT value FROM {inst()})"
CHAR_SQL = f"SELECT value, {', '.join(f'CAST({_COUNT[n]} AS INT) AS n_{n}' for n in CHAR_NAMES)}, " + ", ".join(
    f"CASE WHEN length(value) > 0 THEN round(CAST({_COUNT[n]} AS DOUBLE) / length(value), 4) ELSE 0.0 END AS share_{n}" for n in ("letter", "number")
) + f" FROM {_VALUES_SQL}"
TOKEN_SQL = f"SELECT value, {', '.join(f'CAST({_TOKEN[n]} AS INT) AS n_{n}' for n in TOKEN_TYPES)}, CASE WHEN len(tokens) > 0 THEN round(CAST({_TOKEN['numeric']} AS DOUBLE) / len(tokens), 4) ELSE 0.0 END AS share_numeric FROM (SELECT value, {_TOKENS} AS tokens FROM {_VALUES_SQL})"

_WEIGHTS = (
    f"(SELECT {P}, word, sum(share) AS weight FROM (SELECT {P}, unnest(CASE WHEN len(w) > 0 THEN w ELSE [NULL] END) AS word, 1.0 / greatest(len(w), 1) AS share "
    f"FROM (SELECT {P}, {words('value')} AS w FROM {inst()})) GROUP BY {P}, word)"
)
_LEX = (
    "(SELECT word, list_transform(v, lambda x: x / sqrt(list_sum(list_transform(v, lambda y: y * y)))) AS vec FROM (SELECT word, "
    f"list_transform(list_zip(c.embedding, w.embedding), lambda z: CAST(z[1] AS DOUBLE) * {1 - EPSILON} + CAST(z[2] AS DOUBLE) * {EPSILON}) AS v "
    f"FROM {values(word_concepts(), 'word, concept_id, word_id')} x JOIN embeddings c ON c.vec_id = x.concept_id JOIN embeddings w ON w.vec_id = x.word_id))"
)


def mean_vectors(weights: str, keys: str) -> str:
    """(keys, dim, x): mean vectors in long form. weights: (keys, word, weight)."""
    k = ", ".join(f"w.{c.strip()}" for c in keys.split(","))
    return (
        f"(SELECT {keys}, dim, coalesce(x, 0.0) / total AS x FROM (SELECT {k}, d.dim, sum(w.weight * l.vec[d.dim]) AS x, sum(w.weight) AS total "
        f"FROM {weights} w CROSS JOIN (SELECT unnest(range(1, 65)) AS dim) d LEFT JOIN {_LEX} l ON l.word = w.word GROUP BY {k}, d.dim))"
    )


def digest(long: str) -> str:
    return f"SELECT {P}, round(max(CASE WHEN dim = 1 THEN x END), 4) AS first, round(max(CASE WHEN dim = 64 THEN x END), 4) AS last, round(sqrt(sum(x * x)), 4) AS norm FROM {long} GROUP BY {P}"


_NAME_WEIGHTS = f"(SELECT {P}, unnest(CASE WHEN len(w) > 0 THEN w ELSE [NULL] END) AS word, 1.0 AS weight FROM (SELECT {P}, {words('prop')} AS w FROM {props()}))"

# --- pairs


def combined(mode: str) -> str:
    cols = [*[f"m{i}" for i in range(28)], "num"]
    pairs = paired(f"({profile(inst(), digits=None)})", tuple(cols))
    f = {"abs_diff": "abs({0}_a - {0}_b)", "diff": "{0}_a - {0}_b", "mean": "({0}_a + {0}_b) / 2", "concat": None}[mode]
    xs = [f.format(c) for c in cols] if f else [f"{c}_a" for c in cols] + [f"{c}_b" for c in cols]
    told = lambda x: f"round(sign({x}) * ln(1 + abs({x})), 6) + 0.0"
    return f"SELECT {PAIR}, {len(xs)} AS width, {told(xs[0])} AS first, {told(xs[-1])} AS last, {told(' + '.join(xs))} AS total FROM {pairs}"


_NAMES = f"(SELECT DISTINCT prop_a, prop_b, {normal('prop_a')} AS a, {normal('prop_b')} AS b FROM {paired(props())})"
_GRAM = "CASE WHEN length({0}) >= 3 THEN list_transform(range(1, length({0}) - 1), lambda i: substr({0}, CAST(i AS INT), 3)) WHEN length({0}) > 0 THEN [{0}] ELSE [] END"
_GRAMMED = f"(SELECT *, list_distinct(list_concat(ga, gb)) AS k FROM (SELECT *, {_GRAM.format('a')} AS ga, {_GRAM.format('b')} AS gb FROM {_NAMES}))"
_CA = "len(list_filter(ga, lambda x: x = g))"
_CB = "len(list_filter(gb, lambda x: x = g))"
_DOT = "list_sum(list_transform(k, lambda g: CAST({0} * {1} AS DOUBLE)))"
DISTANCE = {
    "levenshtein": f"SELECT prop_a, prop_b, CAST(levenshtein(a, b) AS DOUBLE) AS dist FROM {_NAMES}",
    "damerau": f"SELECT prop_a, prop_b, CAST(damerau_levenshtein(a, b) AS DOUBLE) AS dist FROM {_NAMES}",
    "jaro_winkler": f"SELECT prop_a, prop_b, round(1 - jaro_winkler_similarity(CASE WHEN length(a) > length(b) OR (length(a) = length(b) AND a > b) THEN a ELSE b END, CASE WHEN length(a) > length(b) OR (length(a) = length(b) AND a > b) THEN b ELSE a END), 6) AS dist FROM {_NAMES}",
    "trigram": f"SELECT prop_a, prop_b, CAST(list_sum(list_transform(k, lambda g: abs({_CA} - {_CB}))) AS DOUBLE) AS dist FROM {_GRAMMED}",
    "trigram_cosine": f"SELECT prop_a, prop_b, round(CASE WHEN a = b THEN 0.0 ELSE 1 - {_DOT.format(_CA, _CB)} / sqrt({_DOT.format(_CA, _CA)} * {_DOT.format(_CB, _CB)}) END, 6) AS dist FROM {_GRAMMED}",
    "trigram_jaccard": f"SELECT prop_a, prop_b, round(1 - CAST(len(list_intersect(list_distinct(ga), list_distinct(gb))) AS DOUBLE) / len(k), 6) AS dist FROM {_GRAMMED}",
}



def _edit_rows(first: str, cell: str, last: str, names: str = _NAMES) -> str:
    """A distance by dynamic programming, a row of the table in each round. cell: of place j, from the row so far (acc), that
    before (prev) and that before it (prev2), for the i-th letter of a; last: the distance."""
    return (
        f"WITH RECURSIVE n AS MATERIALIZED (SELECT * FROM {names}), t AS (SELECT prop_a, prop_b, a, b, 0 AS i, {first} AS prev2, {first} AS prev FROM n UNION ALL "
        f"SELECT prop_a, prop_b, a, b, i + 1, prev, list_reduce(list_concat([[CAST({'i + 1' if 'levenshtein' in last else '0'} AS BIGINT)]], list_transform(range(1, length(b) + 1), lambda x: [x])), "
        f"lambda acc, x: list_append(acc, CAST({cell} AS BIGINT))) FROM t WHERE i < length(a)) "
        f"SELECT prop_a, prop_b, CAST({last.removeprefix('levenshtein:')} AS DOUBLE) AS dist FROM t WHERE i = length(a)"
    )


_J, _EQ = "x[1]", "substr(a, CAST(i + 1 AS INT), 1) = substr(b, CAST(x[1] AS INT), 1)"
DISTANCE["osa"] = _edit_rows(
    "range(0, length(b) + 1)",
    f"least(prev[{_J} + 1] + 1, acc[{_J}] + 1, prev[{_J}] + CASE WHEN {_EQ} THEN 0 ELSE 1 END, CASE WHEN i > 0 AND {_J} > 1 AND substr(a, CAST(i + 1 AS INT), 1) = substr(b, CAST({_J} - 1 AS INT), 1) "
    f"AND substr(a, CAST(i AS INT), 1) = substr(b, CAST({_J} AS INT), 1) THEN prev2[{_J} - 1] + 1 ELSE 9999 END)",
    "levenshtein:prev[-1]",
)
DISTANCE["lcs"] = _edit_rows(
    "list_transform(range(0, length(b) + 1), lambda x: 0)", f"CASE WHEN {_EQ} THEN prev[{_J}] + 1 ELSE greatest(prev[{_J} + 1], acc[{_J}]) END", "length(a) + length(b) - 2 * prev[-1]",
)

# --- splits and samples


def sd_splits(draws: int = 600) -> str:
    """Of so many shuffles of the sources, the first 25 different beginnings."""
    found = f"(SELECT cls, source, count(*) OVER (PARTITION BY cls) AS m FROM (SELECT DISTINCT cls, source FROM {inst()}))"
    parts = values([(f, str(f)) for f in FRACTIONS], "fraction, told")
    base = f"SELECT cls AS dataset, CAST(fraction AS DOUBLE) AS fraction, told, greatest(2, CAST(round_even(CAST(fraction AS DOUBLE) * m, 0) AS INT)) AS k, source AS s FROM {found}, {parts} WHERE m > 1"
    return (
        f"WITH base AS MATERIALIZED ({base}), drawn AS (SELECT dataset, fraction, i, list(s ORDER BY s) AS l FROM (SELECT *, row_number() OVER (PARTITION BY dataset, fraction, i ORDER BY md5('7|' || told || '|' || i || '|' || s)) AS place "
        f"FROM base, range({draws}) d(i)) WHERE place <= k GROUP BY dataset, fraction, i), "
        "ranked AS (SELECT dataset, fraction, l, row_number() OVER (PARTITION BY dataset, fraction ORDER BY min(i)) - 1 AS run FROM drawn GROUP BY dataset, fraction, l) "
        "SELECT r.dataset, r.fraction, CAST(r.run AS INT) AS run, b.s AS source, list_contains(r.l, b.s) AS in_train FROM ranked r JOIN base b ON b.dataset = r.dataset AND b.fraction = r.fraction WHERE r.run < 25"
    )


def sample(domains: tuple[str, ...]) -> str:
    rows = labelled(paired(props(domains)), domains)
    ranked = f"(SELECT *, row_number() OVER (PARTITION BY cls, label ORDER BY md5(concat_ws('|', '7', cls, {PAIR}))) AS r, sum(label) OVER (PARTITION BY cls) AS n FROM {rows})"
    return f"SELECT {PAIR}, label FROM {ranked} WHERE label = 1 OR r <= 2 * n"


_D4 = ("goods", "party", "order", "event")
_TL = (
    f"WITH d AS (SELECT * FROM (SELECT unnest([0, 1, 2, 3]) AS i, unnest({list(_D4)!r}) AS n) SEMI JOIN (SELECT DISTINCT cls AS n FROM {inst()}) USING (n)) "
    "SELECT a.n AS train_set, t.n AS target FROM d a, d t WHERE a.i <> t.i UNION ALL "
    "SELECT a.n || '+' || b.n, t.n FROM d a, d b, d t WHERE a.i < b.i AND t.i NOT IN (a.i, b.i) UNION ALL "
    "SELECT a.n || '+' || b.n || '+' || c.n, t.n FROM d a, d b, d c, d t WHERE a.i < b.i AND b.i < c.i AND t.i NOT IN (a.i, b.i, c.i)"
)

# --- baselines


_CONCEPTS = values([(w, f"concept{c}") for w, c, _ in word_concepts()], "word, concept")


def _lexical(cardinality: str, synonyms: bool = False) -> str:
    base = f"(SELECT {P}, {normal('prop')} AS norm, list_distinct({words('prop')}) AS w FROM {props()})"
    if synonyms:
        base = f"(SELECT {P}, norm, list_sort(list_distinct(list(coalesce(concept, word)))) AS w FROM (SELECT {P}, norm, unnest(w) AS word FROM {base}) LEFT JOIN {_CONCEPTS} USING (word) GROUP BY {P}, norm)"
    sim = f"""WITH base AS {base}, freq AS (SELECT cls, word, count(*) AS f FROM (SELECT cls, unnest(w) AS word FROM base) GROUP BY cls, word),
total AS (SELECT cls, count(*) AS t FROM base GROUP BY cls),
weight AS (SELECT cls, word, CASE WHEN t > 1 THEN 1 - ln(f) / ln(t) ELSE 1.0 END AS r FROM freq JOIN total USING (cls)),
pairs AS (SELECT * FROM {paired('base', ('norm', 'w'))}),
need AS (SELECT DISTINCT cls, w_a, w_b FROM pairs),
mass AS (SELECT n.cls, n.w_a, n.w_b, sum(r) AS every, sum(CASE WHEN list_contains(w_a, word) AND list_contains(w_b, word) THEN r ELSE 0 END) AS shared_mass
 FROM (SELECT cls, w_a, w_b, unnest(list_distinct(list_concat(w_a, w_b))) AS word FROM need) n JOIN weight USING (cls, word) GROUP BY ALL),
scored AS (SELECT {PAIR}, round(CASE WHEN norm_a = norm_b THEN 1.0 ELSE greatest(CASE WHEN every > 0 THEN shared_mass / every ELSE 0.0 END,
 0.8 * (1 - CAST(levenshtein(norm_a, norm_b) AS DOUBLE) / greatest(length(norm_a), length(norm_b), 1))) END, 9) AS score FROM pairs JOIN mass USING (cls, w_a, w_b))
"""
    if cardinality == "n:m":
        return sim + f"SELECT {PAIR}, score, score >= 0.6 AS is_match FROM scored"
    return sim + (
        f"SELECT {PAIR}, score, score >= 0.6 AND row_number() OVER (PARTITION BY cls, source_a, prop_a, source_b ORDER BY score DESC, prop_b) = 1 "
        "AND row_number() OVER (PARTITION BY cls, source_b, prop_b, source_a ORDER BY score DESC, prop_a) = 1 AS is_match FROM scored"
    )


LATTICE = (
    f"WITH s AS (SELECT {PAIR}, len(list_intersect(w_a, w_b)) AS n, len(list_distinct(list_concat(w_a, w_b))) AS u, least(len(w_a), len(w_b)) AS l "
    f"FROM {paired(f'(SELECT {P}, list_distinct({words("prop")}) AS w FROM {props()})', ('w',))}), "
    "m AS (SELECT *, max(n) OVER (PARTITION BY cls, source_a, prop_a, source_b) AS ma, max(n) OVER (PARTITION BY cls, source_b, prop_b, source_a) AS mb FROM s) "
    f"SELECT {PAIR}, CASE WHEN u > 0 THEN CAST(n AS DOUBLE) / u ELSE 0.0 END AS score, n > 0 AND (n = u OR (n = ma AND n = mb AND 2 * n >= l)) AS is_match FROM m"
)
_LONG_NAME = mean_vectors(_NAME_WEIGHTS, P)


def _sem(domains: tuple[str, ...]) -> str:
    return f"""(WITH lex AS MATERIALIZED (SELECT word, dim, vec[dim] AS x FROM {_LEX}, (SELECT unnest(range(1, 65)) AS dim) d),
cosines AS MATERIALIZED (SELECT p.word AS wa, q.word AS wb, sum(p.x * q.x) / sqrt(sum(p.x * p.x) * sum(q.x * q.x)) AS c FROM lex p JOIN lex q USING (dim) GROUP BY p.word, q.word),
names AS MATERIALIZED (SELECT DISTINCT {normal('prop')} AS n FROM {props(domains)}), parts AS (SELECT n, unnest({words('n')}) AS word FROM names),
coherent AS MATERIALIZED (SELECT p.n AS n_a, q.n AS n_b, round(avg(c), 9) AS coherence FROM parts p JOIN cosines ON wa = p.word JOIN parts q ON wb = q.word GROUP BY p.n, q.n)
SELECT {PAIR}, round(1 - CAST(levenshtein(x.n_a, x.n_b) AS DOUBLE) / greatest(length(x.n_a), length(x.n_b), 1), 9) AS syn, coherence
FROM {paired(f'(SELECT *, {normal("prop")} AS n FROM {props(domains)})', ('n',))} x LEFT JOIN coherent c ON c.n_a = x.n_a AND c.n_b = x.n_b)"""


_LINK = "(syn >= {0} AND NOT coalesce(coherence < {1}, false)) OR coalesce(coherence >= {2}, false)"
SEMGRAPH = f"SELECT {PAIR}, greatest(syn, coalesce(coherence, 0.0)) AS score, {_LINK.format(semgraph.SYN, semgraph.NEG, semgraph.POS)} AS is_match FROM {_sem(ALL)}"


def _f1(tp: str, fp: str, fn: str) -> str:
    return f"CASE WHEN 2 * {tp} + {fp} + {fn} > 0 THEN 2.0 * {tp} / (2 * {tp} + {fp} + {fn}) ELSE 0.0 END"


_GRID = values([(a, b, c) for a in semgraph.GRID for b in semgraph.GRID for c in semgraph.GRID], "syn_t, neg_t, pos_t")
SEMGRAPH_SWEEP = (
    f"SELECT syn_t, neg_t, pos_t, round(avg(f1), 4) AS mean_f1 FROM (SELECT cls, syn_t, neg_t, pos_t, {_f1('tp', 'fp', 'fn')} AS f1 FROM "
    "(SELECT cls, CAST(syn_t AS DOUBLE) AS syn_t, CAST(neg_t AS DOUBLE) AS neg_t, CAST(pos_t AS DOUBLE) AS pos_t, sum(CASE WHEN m AND label = 1 THEN 1 ELSE 0 END) AS tp, sum(CASE WHEN m AND label = 0 THEN 1 ELSE 0 END) AS fp, sum(CASE WHEN NOT m AND label = 1 THEN 1 ELSE 0 END) AS fn "
    f"FROM (SELECT *, {_LINK.format('syn_t', 'neg_t', 'pos_t')} AS m FROM {labelled(_sem(ALL), ALL)}, {_GRID}) GROUP BY ALL)) GROUP BY ALL"
)
COSINE = (
    f"WITH v AS MATERIALIZED (SELECT {P}, dim, x FROM {_LONG_NAME}), n AS MATERIALIZED (SELECT DISTINCT prop FROM v), one AS MATERIALIZED (SELECT DISTINCT prop, dim, x FROM v), "
    "c AS MATERIALIZED (SELECT a.prop AS prop_a, b.prop AS prop_b, CASE WHEN sum(a.x * a.x) * sum(b.x * b.x) > 0 THEN sum(a.x * b.x) / sqrt(sum(a.x * a.x) * sum(b.x * b.x)) ELSE 0.0 END AS s FROM one a JOIN one b USING (dim) GROUP BY a.prop, b.prop) "
    f"SELECT {PAIR}, round(s, 9) AS score, round(s, 9) >= 0.6 AS is_match FROM {paired(props())} JOIN c USING (prop_a, prop_b)"
)


def _hashes(variant: str, n: int, domains: tuple[str, ...], alias: str = "sig") -> str:
    ab = values([(i, a, b) for i, (a, b) in enumerate(lsh.coefficients(n))], "i, a, b")
    element = f"SELECT {P}, word, count(*) AS n FROM (SELECT {P}, unnest({words('value')}) AS word FROM {inst(domains)}) GROUP BY {P}, word"
    h = f"(SELECT {P}, n, CAST('0x' || substr(md5(word), 1, 8) AS BIGINT) % {lsh.PRIME} AS h FROM ({element}))"
    if variant == "minhash":
        return f"{alias} AS MATERIALIZED (SELECT {P}, i, min((h * a + b) % {lsh.PRIME}) AS s FROM {h}, {ab} GROUP BY {P}, i)"
    return f"{alias} AS MATERIALIZED (SELECT {P}, i, CASE WHEN sum(CASE WHEN ((h * a + b) % {lsh.PRIME}) % 2 = 0 THEN n ELSE -n END) >= 0 THEN 1 ELSE 0 END AS s FROM {h}, {ab} GROUP BY {P}, i)"


def _lsh(variant: str, n: int, band: int, domains: tuple[str, ...]) -> str:
    score = f"CAST(eq AS DOUBLE) / {n}" if variant == "minhash" else f"round(cos(3.141592653589793 * ({n} - eq) / {n}), 9)"
    return (
        f"WITH {_hashes(variant, n, domains)}, equal AS (SELECT a.cls, a.source AS source_a, a.prop AS prop_a, b.source AS source_b, b.prop AS prop_b, a.i, (a.s = b.s) AS e FROM sig a JOIN sig b ON a.cls = b.cls AND a.source < b.source AND a.i = b.i), "
        f"band AS (SELECT {PAIR}, i // {band} AS no, sum(e::INT) AS hit FROM equal GROUP BY ALL), total AS (SELECT {PAIR}, sum(hit) AS eq, max(CASE WHEN hit = {band} THEN 1 ELSE 0 END) AS found FROM band GROUP BY ALL) "
        f"SELECT {PAIR}, {score} AS score, true AS is_match FROM total WHERE found = 1"
    )


_BANDS = values([(b,) for b in lsh.BANDS], "band")


def _lsh_sweep() -> str:
    """Per pair the equal places as a text of 0 and 1; a pair is found where a whole band of it is 1."""
    parts = []
    for v, n in lsh.HASHES.items():
        parts.append(
            f"SELECT '{v}' AS variant, {n} AS n, a.cls, a.source AS source_a, a.prop AS prop_a, b.source AS source_b, b.prop AS prop_b, "
            f"array_to_string(list_transform(list_zip(a.l, b.l), lambda z: CASE WHEN z[1] = z[2] THEN '1' ELSE '0' END), '') AS e FROM list_{v} a JOIN list_{v} b ON a.cls = b.cls AND a.source < b.source"
        )
    sigs = ", ".join(f"{_hashes(v, n, ALL, f'sig_{v}')}, list_{v} AS MATERIALIZED (SELECT {P}, list(s ORDER BY i) AS l FROM sig_{v} GROUP BY {P})" for v, n in lsh.HASHES.items())
    return (
        f"WITH {sigs}, eq AS MATERIALIZED ({' UNION ALL '.join(parts)}), hit AS (SELECT variant, band, {PAIR} FROM eq, {_BANDS} "
        "WHERE list_contains(list_transform(range(0, n // band), lambda k: substr(e, CAST(k * band + 1 AS INT), CAST(band AS INT)) = repeat('1', CAST(band AS INT))), true)), "
        f"real AS MATERIALIZED (SELECT *, 1 AS t FROM {truth()}), c AS (SELECT variant, band, cls, count(t) AS tp, count(*) - count(t) AS fp FROM hit LEFT JOIN real USING ({PAIR}) GROUP BY ALL), "
        "all_ AS (SELECT cls, count(*) AS n FROM real GROUP BY cls), "
        f"f AS (SELECT variant, band, {_f1('tp', 'fp', '(n - tp)')} AS f1 FROM c JOIN all_ USING (cls)) SELECT variant, CAST(band AS INT) AS band, round(sum(f1) / {len(ALL)}, 4) AS mean_f1 FROM f GROUP BY variant, band"
    )


# --- measures


def prf(parts: dict[str, str]) -> str:
    rows = " UNION ALL ".join(f"SELECT '{n}' AS method, {PAIR} FROM ({q}) WHERE is_match" for n, q in parts.items())
    return (
        f"WITH found AS MATERIALIZED ({rows}), real AS MATERIALIZED (SELECT n.method, t.* FROM {truth()} t, {values([(n,) for n in parts], 'method')} n), "
        f"j AS (SELECT coalesce(f.cls, r.cls) AS cls, coalesce(f.method, r.method) AS method, f.cls IS NOT NULL AS m, r.cls IS NOT NULL AS t FROM found f FULL OUTER JOIN real r ON f.method = r.method AND {' AND '.join(f'f.{c} = r.{c}' for c in PAIR.split(', '))}), "
        "c AS (SELECT cls, method, CAST(sum((m AND t)::INT) AS BIGINT) AS tp, CAST(sum((m AND NOT t)::INT) AS BIGINT) AS fp, CAST(sum((NOT m AND t)::INT) AS BIGINT) AS fn FROM j GROUP BY ALL) "
        "SELECT cls, tp, fp, fn, round(CASE WHEN tp + fp > 0 THEN CAST(tp AS DOUBLE) / (tp + fp) ELSE 0.0 END, 4) AS precision, "
        f"round(CASE WHEN tp + fn > 0 THEN CAST(tp AS DOUBLE) / (tp + fn) ELSE 0.0 END, 4) AS recall, round({_f1('tp', 'fp', 'fn')}, 4) AS f1, method FROM c"
    )


PRF = prf({"lexical": _lexical("1:1"), "lattice": LATTICE, "semgraph": SEMGRAPH})
CLUSTERS = (
    f"WITH RECURSIVE m AS MATERIALIZED (SELECT concat_ws('/', cls, source_a, prop_a) AS a, concat_ws('/', cls, source_b, prop_b) AS b, {PAIR} FROM ({LATTICE}) WHERE is_match), "
    "e AS MATERIALIZED (SELECT a, b FROM m UNION SELECT b, a FROM m), r AS (SELECT a AS n, a AS l FROM e UNION SELECT e.b, r.l FROM r JOIN e ON e.a = r.n), "
    "nodes AS (SELECT cls, source_a AS source, prop_a AS prop FROM m UNION SELECT cls, source_b, prop_b FROM m) "
    "SELECT cls, source, prop, min(l) AS cluster_id FROM nodes JOIN r ON r.n = concat_ws('/', cls, source, prop) GROUP BY cls, source, prop"
)


def _ways(sim: str) -> str:
    return f"(WITH sim AS MATERIALIZED ({sim}) SELECT cls, source_a AS source, prop_a AS prop, source_b AS other_source, prop_b AS other_prop, score, is_match FROM sim UNION ALL SELECT cls, source_b, prop_b, source_a, prop_a, score, is_match FROM sim)"


TOPK = f"SELECT {P}, other_source, other_prop, score, CAST(row_number() OVER (PARTITION BY {P} ORDER BY score DESC, other_source, other_prop) AS INT) AS rank FROM {_ways(COSINE)} QUALIFY rank <= 3"
EQUAL = (
    f"SELECT {PAIR}, score, is_match FROM ({_lexical('n:m')}) WHERE is_match QUALIFY row_number() OVER (PARTITION BY cls, source_a, prop_a, source_b ORDER BY score DESC, prop_a, prop_b) = 1 "
    "AND row_number() OVER (PARTITION BY cls, source_b, prop_b, source_a ORDER BY score DESC, prop_a, prop_b) = 1"
)
_DEALT = (
    f"split AS MATERIALIZED (SELECT * FROM ({sd_splits()})), p AS MATERIALIZED (SELECT * FROM {labelled(paired(props()), ALL)}), "
    "dealt AS (SELECT a.dataset, a.fraction, a.run, a.in_train AND b.in_train AS both_, a.in_train OR b.in_train AS one, label "
    "FROM p JOIN split a ON a.dataset = p.cls AND a.source = p.source_a JOIN split b ON b.dataset = p.cls AND b.source = p.source_b AND a.fraction = b.fraction AND a.run = b.run)"
)
SPLIT_PAIRS = (
    f"WITH {_DEALT} SELECT dataset, fraction, run, count(*) FILTER (both_) AS n_train, count(*) FILTER (both_ AND label = 1) AS n_train_matches, "
    "count(*) FILTER (NOT both_) AS n_test, count(*) FILTER (NOT one) AS n_unseen FROM dealt GROUP BY dataset, fraction, run"
)
RUN_SIZES = f"WITH {_DEALT} SELECT dataset, fraction, run, count(*) FILTER (NOT both_) AS n_test, count(*) FILTER (NOT both_ AND label = 1) AS n_test_matches FROM dealt GROUP BY dataset, fraction, run"


def _mean(c: str) -> str:
    return f"CAST(sum(CAST({c} AS DECIMAL(18, 12))) AS DOUBLE) / count(*) AS mean_{c}"


PR_CURVE = (
    f"WITH real AS MATERIALIZED (SELECT *, 1 AS t FROM {truth()}), step AS (SELECT cls, score, count(t) AS t, count(*) AS n FROM ({_lexical('n:m')}) LEFT JOIN real USING ({PAIR}) GROUP BY cls, score), "
    "total AS (SELECT cls, count(*) AS every FROM real GROUP BY cls), "
    "down AS (SELECT cls, score, CAST(sum(t) OVER w AS BIGINT) AS tp, CAST(sum(n) OVER w AS BIGINT) AS seen FROM step WINDOW w AS (PARTITION BY cls ORDER BY score DESC ROWS UNBOUNDED PRECEDING)) "
    "SELECT cls, score, tp, seen - tp AS fp, round(CAST(tp AS DOUBLE) / seen, 4) AS precision, round(CAST(tp AS DOUBLE) / every, 4) AS recall FROM down JOIN total USING (cls)"
)
_FLAT = {
    "lexical_onto": _lexical("1:1"), "concept_lattice": LATTICE, "semantic_graph": SEMGRAPH, "lsh_instances": _lsh("minhash", lsh.HASHES["minhash"], 1, ALL), "cosine": COSINE,
}
FLAT = f"SELECT cls AS dataset, method, tp, fp, fn, precision, recall, f1 FROM ({prf(_FLAT)})"
FUSED = (
    f"WITH c AS MATERIALIZED (SELECT * FROM ({CLUSTERS}) WHERE cls = 'goods'), v AS (SELECT cls, cluster_id, entity, value, count(*) AS n FROM {inst(('goods',))} JOIN c USING ({P}) GROUP BY ALL) "
    "SELECT cls, cluster_id, entity, value, n FROM v QUALIFY row_number() OVER (PARTITION BY cls, cluster_id, entity ORDER BY n DESC, value) = 1"
)
_PLAIN = f"(SELECT {P}, m1, num FROM ({profile(inst(), digits=None)}))"
_VECTOR = lambda long, dim: f"(SELECT {P}, x FROM {long} WHERE dim = {dim})"
_VALUE_LONG = mean_vectors(_WEIGHTS, P)
_SIDES = " ".join(
    f"JOIN {rel} {n}{s} ON {n}{s}.cls = s.cls AND {n}{s}.source = s.source_{s} AND {n}{s}.prop = s.prop_{s}"
    for s in "ab" for n, rel in (("p", _PLAIN), ("v", _VECTOR(_VALUE_LONG, 4)), ("w", _VECTOR(_LONG_NAME, 2)))
)
SAMPLED = (
    f"SELECT s.*, label, CAST(levenshtein({normal('s.prop_a')}, {normal('s.prop_b')}) AS DOUBLE) AS levenshtein, round(abs(pa.m1 - pb.m1), 4) AS letter_share, round(abs(pa.num - pb.num), 4) AS number, "
    f"round(abs(va.x - vb.x), 4) AS value_vector_4, round(abs(wa.x - wb.x), 4) AS name_vector_2 FROM {values([('goods', *x) for x in SAMPLE], PAIR)} s {_SIDES} "
    f"JOIN {labelled(paired(props(('goods',))), ('goods',))} l ON {' AND '.join(f'l.{c} = s.{c}' for c in PAIR.split(', '))}"
)
_STREAM_FIELDS = {"user": "CAST(user_id AS VARCHAR)", "event type": "event_type", "amount": "CAST(CAST(value AS DECIMAL(18, 2)) AS VARCHAR)", "key": "json_extract_string(props, '$.k')"}
_STREAM = "(SELECT * FROM (" + " UNION ALL ".join(
    f"SELECT 'event' AS cls, 'e' || lpad(CAST(user_id % 8 AS VARCHAR), 2, '0') AS source, '{n}' AS prop, {v} AS value FROM events" for n, v in _STREAM_FIELDS.items()
) + ") WHERE value IS NOT NULL)"
_REAL_WAYS = f"(SELECT cls, source_a AS source, prop_a AS prop, source_b AS other_source, prop_b AS other_prop FROM {truth(('order',))} UNION ALL SELECT cls, source_b, prop_b, source_a, prop_a FROM {truth(('order',))})"
ONE_TO_MANY = f"SELECT {P}, other_source, string_agg(other_prop, '|' ORDER BY other_prop) AS partners, count(*) AS n_partners FROM {_REAL_WAYS} JOIN {props(('order',))} USING ({P}) GROUP BY {P}, other_source HAVING count(*) > 1"

_EIGHT = f"names AS MATERIALIZED (SELECT * FROM {_NAMES}), " + ", ".join(f"d_{k} AS MATERIALIZED ({DISTANCE[k]})" for k in strings.DISTANCES)
_JOINED = " ".join(f"JOIN d_{k} USING (prop_a, prop_b)" for k in strings.DISTANCES)
_DISTANCES = ", ".join(f"d_{k}.dist AS dist_{k}" for k in strings.DISTANCES)
ASSEMBLED = (
    f"WITH {_EIGHT}, prof AS MATERIALIZED {_PLAIN} SELECT {PAIR}, {29 + 2 * 64 + 8} AS width, round(abs(m1_a - m1_b), 9) AS letter_share, round(ln(1 + abs(num_a - num_b)), 6) AS number, "
    + ", ".join(f"round(d_{k}.dist, 6) AS dist_{k}" for k in strings.DISTANCES) + f" FROM {paired('prof', ('m1', 'num'))} x {_JOINED}"
)


def _ruled() -> str:
    """Scores of the network of experiments.ruled_network: a first layer over long features, the others written out."""
    net = ruled_network(29 + 2 * 64 + 8)
    first = values([(i, *map(float, row)) for i, row in enumerate(net.weights[0])], "i, " + ", ".join(f"u{j}" for j in range(8)))
    long = (
        f"SELECT {P}, i, x FROM (UNPIVOT (SELECT {P}, {', '.join(f'm{k}' for k in range(28))}, num AS m28 FROM ({profile(inst(), digits=None)})) ON {', '.join(f'm{k}' for k in range(29))} INTO NAME f VALUE x), "
        f"LATERAL (SELECT CAST(substr(f, 2) AS BIGINT) AS i) UNION ALL SELECT {P}, 28 + dim, x FROM {_VALUE_LONG} UNION ALL SELECT {P}, 92 + dim, x FROM {_LONG_NAME}"
    )
    layer = lambda k, width, names: [f"{net.biases[k][j]} + " + " + ".join(f"({float(w)}) * {n}" for w, n in zip(net.weights[k][:, j], names, strict=True)) for j in range(width)]
    eight = " + ".join(f"d_{k}.dist * ({{{i}}})" for i, k in enumerate(strings.DISTANCES))
    h0 = ", ".join(f"greatest(0, {net.biases[0][j]} + s{j} + {eight.format(*map(float, net.weights[0][-8:, j]))}) AS h{j}" for j in range(8))
    h1 = ", ".join(f"greatest(0, {e}) AS g{j}" for j, e in enumerate(layer(1, 4, [f"h{j}" for j in range(8)])))
    z = layer(2, 2, [f"g{j}" for j in range(4)])
    return (
        f"WITH {_EIGHT}, long AS MATERIALIZED ({long}), u AS MATERIALIZED {first}, "
        f"part AS (SELECT a.cls, a.source AS source_a, a.prop AS prop_a, b.source AS source_b, b.prop AS prop_b, {', '.join(f'sum(abs(a.x - b.x) * u{j}) AS s{j}' for j in range(8))} "
        f"FROM long a JOIN long b ON a.cls = b.cls AND a.i = b.i AND a.source < b.source JOIN u ON u.i = a.i GROUP BY ALL), "
        f"one AS (SELECT {PAIR}, {h0} FROM part {_JOINED}), two AS (SELECT {PAIR}, {h1} FROM one), out_ AS (SELECT {PAIR}, {z[0]} AS z0, {z[1]} AS z1 FROM two) "
        f"SELECT {PAIR}, round(1 / (1 + exp(z0 - z1)), 5) AS score FROM out_"
    )


FIXED = _ruled()

ORACLE: dict[str, str] = {
    **{f"instances_{c}": instances_sql(c) for c in (*ALL, "text")},
    "property_catalog": f"SELECT {P}, count(*) AS n_instances, count(DISTINCT entity) AS n_entities, count(DISTINCT value) AS n_values FROM {inst()} GROUP BY {P}",
    "dataset_statistics": f"SELECT s.*, coalesce(n_matching_pairs, 0) AS n_matching_pairs FROM (SELECT cls, count(DISTINCT source) AS n_sources, count(DISTINCT source || '|' || prop) AS n_properties, count(DISTINCT source || '|' || entity) AS n_entities FROM {inst()} GROUP BY cls) s LEFT JOIN (SELECT cls, count(*) AS n_matching_pairs FROM {truth()} GROUP BY cls) t USING (cls)",
    "source_statistics": f"SELECT cls, source, count(DISTINCT prop) AS n_properties, count(DISTINCT entity) AS n_entities, count(*) AS n_instances FROM {inst()} GROUP BY cls, source",
    "entity_cap": f"SELECT source, count(DISTINCT entity) AS n_entities FROM {inst(('goods',))} GROUP BY source",
    "char_features": CHAR_SQL, "token_features": TOKEN_SQL,
    "numeric_feature": f"SELECT value, round({_NUM}, 4) AS num FROM {_VALUES_SQL}",
    "value_word_weights": f"SELECT {P}, coalesce(word, '') AS word, round(weight, 4) AS weight FROM {_WEIGHTS}",
    "value_embedding": digest(mean_vectors(_WEIGHTS, P)), "name_embedding": digest(_LONG_NAME),
    "property_profile": profile(inst()),
    **{f"profile_{a}": profile(inst(), a) for a in ("min", "max")},
    "profile_stddev": profile(inst(), "stddev_pop"),
    "profile_distinct": profile(f"(SELECT DISTINCT {P}, value FROM {inst()})"),
    "candidate_pairs": f"SELECT * FROM {paired(props())}", "candidate_pairs_blocks": f"SELECT * FROM {paired(props())}",
    "truth_pairs": f"WITH found AS MATERIALIZED {props()} SELECT t.* FROM {truth()} t SEMI JOIN found a ON t.cls = a.cls AND t.source_a = a.source AND t.prop_a = a.prop SEMI JOIN found b ON t.cls = b.cls AND t.source_b = b.source AND t.prop_b = b.prop", "labelled_pairs": f"SELECT * FROM {labelled(paired(props()), ALL)}",
    **{f"pair_{m}": combined(m) for m in ("abs_diff", "diff", "mean", "concat")},
    **{f"dist_{k}": q for k, q in DISTANCE.items()},
    "sd_splits": sd_splits(), "split_pairs": SPLIT_PAIRS, "tl_combinations": _TL,
    "negative_sample": f"SELECT * FROM ({sample(ALL)}) WHERE label = 0", "training_pairs": sample(ALL),
    "lexical_alike": f"SELECT * FROM ({_lexical('1:1')}) WHERE score >= 0.6", "lexical_alike_many": f"SELECT * FROM ({_lexical('n:m')}) WHERE score >= 0.6",
    "lattice_sharing": f"SELECT * FROM ({LATTICE}) WHERE score > 0", "cosine_alike": f"SELECT * FROM ({COSINE}) WHERE is_match",
    "baseline_lexical": _lexical("1:1"), "baseline_lexical_many": _lexical("n:m"), "baseline_lattice": LATTICE, "baseline_semgraph": SEMGRAPH, "semgraph_sweep": SEMGRAPH_SWEEP,
    "baseline_minhash": _lsh("minhash", lsh.HASHES["minhash"], 1, ALL), "baseline_projection": _lsh("projection", lsh.HASHES["projection"], 20, ALL),
    "baseline_cosine": COSINE, "metrics_prf": PRF,
    "best_config": f"SELECT * FROM ({PRF}) QUALIFY rank() OVER (PARTITION BY cls ORDER BY f1 DESC) = 1",
    "f1_gap": f"WITH p AS MATERIALIZED ({PRF}) SELECT a.cls, a.method, round(100 * (b.f1 - a.f1), 2) AS gap_points FROM p a JOIN p b ON a.cls = b.cls AND b.method = 'semgraph' WHERE a.method <> 'semgraph'",
    "metrics_cube": f"SELECT cls, method, count(*) AS n, {_mean('precision')}, {_mean('recall')}, {_mean('f1')} FROM ({PRF}) GROUP BY CUBE (cls, method)",
    "pr_curve": PR_CURVE, "flat_baselines": FLAT, "fused_values": FUSED, "sample_features": SAMPLED, "stream_profile": profile(_STREAM), "lsh_sweep": _lsh_sweep(),
    "baseline_lexical_synonyms": _lexical("1:1", True), "profile_median": profile(inst(), "median"), "run_sizes": RUN_SIZES,
    "similarity_graph": f"SELECT * FROM ({_lexical('n:m')}) WHERE score >= 0.5", "one_to_many": ONE_TO_MANY, "assembled_features": ASSEMBLED, "ppc_fixed": FIXED,
    "clusters_transitive": CLUSTERS, "partners_topk": TOPK,
    "partners_many": f"SELECT {P}, other_source, string_agg(other_prop, '|' ORDER BY other_prop) AS partners, count(*) AS n_partners FROM {_ways(LATTICE)} WHERE is_match GROUP BY {P}, other_source",
    "equal_matches": EQUAL,
}
