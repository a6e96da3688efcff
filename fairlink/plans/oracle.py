"""DuckDB SQL of the pipeline's steps, as common table expressions to build oracles from."""

from __future__ import annotations

from fairlink.functions import theory
from fairlink.settings import DEFAULT, LEXICON, Linkage
from fairlink.sources.people import MEN, SEED


def u(purpose: str, *keys: str, seed: int = SEED, start: int = 1) -> str:
    text = " || '|' || ".join([f"'{seed}|{purpose}'", *(f"({k})::VARCHAR" for k in keys)])
    return f"((('0x' || substr(md5({text}), {start}, 13))::BIGINT + 0.5) / 4503599627370496.0)"


def lap(draw: str, scale: str) -> str:
    return f"(-({scale}) * sign({draw} - 0.5) * ln(1 - 2 * abs({draw} - 0.5)))"


def grams(column: str, prefix: str, q: int = 2) -> str:
    value = f"trim(regexp_replace(lower(coalesce({column}, '')), '[.,;:''\"-]', '', 'g'))"
    return f"CASE WHEN {value} = '' THEN [] WHEN length({value}) < {q} THEN ['{prefix}' || {value}] ELSE list_transform(range(1, length({value}) - {q - 2}), lambda i: '{prefix}' || substr({value}, i, {q})) END"


def word(purpose: str, key: str) -> str:
    d = u(purpose, key)
    return f"words[1 + floor({d} * {d} * len(words))::INTEGER]"


TOKENS = "list_distinct(list_concat(" + ", ".join(grams(c, p) for c, p in (("given", "g:"), ("surname", "s:"), ("suburb", "b:"), ("postcode", "p:"))) + ", ['x:' || gender]))"
CENSUS = "list_distinct(list_concat(['a:' || area, 'm:' || mesh, 'x:' || gender, 'f:' || full_time::VARCHAR], list_transform(industries, lambda v: 'i:' || v)))"
MEN_SQL = ", ".join(f"'{m}'" for m in MEN)


def encoded(source: str, tokens: str = TOKENS, k: int = DEFAULT.k_hash, rounds: int = 1) -> str:
    """Filter words of the rows of a step with party, rec_id, entity_id, group_id."""
    words = ", ".join(f"coalesce(bit_or(CASE WHEN pos // 60 = {i} THEN (1::BIGINT << (pos % 60)::INTEGER) ELSE 0 END), 0)::BIGINT AS w{i}" for i in range(5))
    return f"""
    SELECT party, rec_id, any_value(entity_id) AS entity_id, any_value(group_id) AS group_id, {words} FROM (
        SELECT party, rec_id, entity_id, group_id, (('0x' || substr(md5(secret || '|' || token), 1, 13))::BIGINT + i * ('0x' || substr(md5(secret || '|' || token), 14, 13))::BIGINT) % {DEFAULT.n_bits} AS pos
        FROM (SELECT party, rec_id, entity_id, group_id, unnest({tokens}) AS token FROM {source}), range({k}) r(i), (VALUES {', '.join(f"('{DEFAULT.secret}{'' if n == 0 else f'#{n}'}')" for n in range(rounds))}) v(secret)
    ) GROUP BY party, rec_id"""


def label(table: int, settings: Linkage = DEFAULT) -> str:
    return "(" + " + ".join(f"(((w{p // 60} >> {p % 60}) & 1) << {j})" for j, p in enumerate(settings.label_positions(table))) + ")"


ONES = " + ".join(f"bit_count(w{i})::INTEGER" for i in range(5))
EARLIER = " OR ".join(f"(a.table_no > {t} AND a.l{t} = b.l{t})" for t in range(DEFAULT.label_tables))
COMMON = "(" + " + ".join(f"bit_count(a.w{i} & b.w{i})::INTEGER" for i in range(5)) + ")"


def mask(word_no: int, flip: str) -> str:
    key = f"'{DEFAULT.seed}|flip|' || rec_id || '|' || table_no::VARCHAR || '|{word_no}|' || i::VARCHAR"
    bit = lambda start, at: f"(CASE WHEN ((('0x' || substr(md5({key}), {start}, 13))::BIGINT + 0.5) / 4503599627370496.0) < {flip} THEN (1::BIGINT << ({at})::INTEGER) ELSE 0 END)"
    return f"xor(w{word_no}, (SELECT sum({bit(1, '2 * i')} + {bit(14, '2 * i + 1')})::BIGINT FROM range(30) r(i)))"


def noise_sql(eps: str = "2.0", rounding: str = "floor(x + 0.5)", cap: str = "least(n, greatest(0, m))", key: str = "party, table_no, label, group_id") -> str:
    draw = u("noise", *key.split(", "))
    return f"SELECT * EXCLUDE (x, m), ({cap})::BIGINT AS m FROM (SELECT *, {rounding} AS m FROM (SELECT *, {lap(draw, f'{DEFAULT.sensitivity} / {eps}')} AS x FROM STATS))"


STEPS: dict[str, str] = {
    "lex": f"SELECT word, n, place FROM (SELECT word, n, row_number() OVER (ORDER BY n DESC, word) - 1 AS place FROM (SELECT word, count(*) AS n FROM (SELECT unnest(string_split_regex(text, '[ \\n]')) AS word FROM documents WHERE lang = 'en') WHERE regexp_full_match(word, '[a-z]{{3,10}}') GROUP BY word)) WHERE place < {LEXICON}",
    "lexs": "SELECT list(word ORDER BY place) AS words FROM lex",
    "ord": "SELECT o_custkey, list_sort(list(DISTINCT o_orderpriority)) AS industries, count(*) AS orders FROM orders GROUP BY o_custkey",
    "people": f"""
    SELECT c_custkey::BIGINT AS entity_id, {word('given', 'c_custkey')} AS given, {word('surname', 'c_custkey')} AS surname, {word('suburb', 'c_nationkey')} AS suburb,
        lpad((c_nationkey * 100 + floor({u('postcode', 'c_custkey')} * 100)::BIGINT)::VARCHAR, 4, '0') AS postcode,
        CASE WHEN c_mktsegment IN ({MEN_SQL}) THEN 'm' ELSE 'w' END AS gender, (18 + floor((c_acctbal + 1000) / 11000 * 72))::INTEGER AS age,
        coalesce(industries, []) AS industries, coalesce(orders, 0) >= 10 AS full_time, r_name AS area, n_name AS mesh,
        (('0x' || substr(md5('{SEED}|party|' || c_custkey::VARCHAR), 1, 13))::BIGINT % 3)::INTEGER AS lot
    FROM customer JOIN nation ON c_nationkey = n_nationkey JOIN region ON n_regionkey = r_regionkey LEFT JOIN ord ON c_custkey = o_custkey, lexs""",
    "recs": "SELECT *, gender AS group_id, party || '-' || entity_id::VARCHAR AS rec_id FROM (SELECT *, 'A' AS party FROM people WHERE lot <> 2 UNION ALL SELECT *, 'B' AS party FROM people WHERE lot <> 1)",
    "enc": f"SELECT *, ({ONES})::INTEGER AS n_ones FROM ({encoded('recs')})",
    "lab": "SELECT *, " + ", ".join(f"{label(t)}::BIGINT AS l{t}" for t in range(DEFAULT.label_tables)) + " FROM enc",
    "blk": "SELECT lab.*, t::INTEGER AS table_no, CASE t " + " ".join(f"WHEN {t} THEN l{t}" for t in range(DEFAULT.label_tables)) + f" END AS label FROM lab, range({DEFAULT.label_tables}) r(t)",
    "stats": "SELECT party, table_no, label, group_id, count(*) AS n FROM blk GROUP BY ALL",
    "counts": noise_sql().replace("STATS", "stats"),
    "chosen": f"SELECT blk.*, md5('{DEFAULT.seed}|pick|' || rec_id || '|' || table_no::VARCHAR) AS o, m FROM blk JOIN (SELECT party, table_no, label, group_id, m FROM counts WHERE m > 0) USING (party, table_no, label, group_id) QUALIFY row_number() OVER (PARTITION BY party, table_no, label, group_id ORDER BY o) <= m",
    "dums": "SELECT *, (" + ONES + f")::INTEGER AS n_ones FROM (SELECT party, 'd-' || substr(md5('{DEFAULT.seed}|dummy|' || rec_id || '|' || table_no::VARCHAR), 1, 16) AS rec_id, rec_id AS parent_id, entity_id, group_id, table_no, label, " + ", ".join(f"l{t}" for t in range(DEFAULT.label_tables)) + ", " + ", ".join(f"{mask(i, str(DEFAULT.flip))} AS w{i}" for i in range(5)) + " FROM chosen)",
    "noisy": "SELECT party, rec_id, entity_id, group_id, w0, w1, w2, w3, w4, n_ones, l0, l1, l2, l3, l4, table_no, label, false AS is_dummy FROM blk UNION ALL SELECT party, rec_id, entity_id, group_id, w0, w1, w2, w3, w4, n_ones, l0, l1, l2, l3, l4, table_no, label, true FROM dums",
    "pairs": "PAIRS(blkd)",
    "blkd": "SELECT *, false AS is_dummy FROM blk",
    "npairs": "PAIRS(noisy)",
    "truth": "SELECT a.rec_id AS id_a, b.rec_id AS id_b, a.group_id FROM recs a JOIN recs b ON a.party = 'A' AND b.party = 'B' AND a.entity_id = b.entity_id",
    "conf": "CONF(pairs)",
    "nconf": "CONF(npairs)",
}


def _pairs(source: str, scope: str = "AND a.group_id = b.group_id") -> str:
    return f"""
    SELECT table_no, label, id_a, id_b, group_id, fake, truth, common, ones_a, ones_b, CASE WHEN ones_a + ones_b = 0 THEN 0.0 ELSE 2.0 * common / (ones_a + ones_b) END AS sim FROM (
        SELECT a.table_no, a.label, a.rec_id AS id_a, b.rec_id AS id_b, a.group_id, a.is_dummy OR b.is_dummy AS fake, NOT (a.is_dummy OR b.is_dummy) AND a.entity_id = b.entity_id AS truth,
            {COMMON} AS common, a.n_ones AS ones_a, b.n_ones AS ones_b
        FROM {source} a JOIN {source} b ON a.party = 'A' AND b.party = 'B' AND a.table_no = b.table_no AND a.label = b.label {scope}
        WHERE a.is_dummy OR b.is_dummy OR NOT ({EARLIER}))"""


def _conf(source: str, pred: str = "sim > 0.8") -> str:
    return f"""
    SELECT coalesce(p.group_id, t.group_id) AS group_id, coalesce(tp, 0)::BIGINT AS tp, coalesce(fp, 0)::BIGINT AS fp, coalesce(tn, 0)::BIGINT AS tn, (coalesce(every, 0) - coalesce(tp, 0))::BIGINT AS fn
    FROM (SELECT group_id, count(*) FILTER (WHERE {pred} AND truth) AS tp, count(*) FILTER (WHERE {pred} AND NOT truth) AS fp, count(*) FILTER (WHERE NOT ({pred}) AND NOT truth) AS tn FROM {source} GROUP BY group_id) p
    FULL JOIN (SELECT group_id, count(*) AS every FROM truth GROUP BY group_id) t ON p.group_id = t.group_id"""


NEEDS = {
    "lexs": ["lex"], "people": ["lexs", "ord"], "recs": ["people"], "enc": ["recs"], "lab": ["enc"], "blk": ["lab"], "stats": ["blk"], "counts": ["stats"],
    "chosen": ["blk", "counts"], "dums": ["chosen"], "noisy": ["blk", "dums"], "blkd": ["blk"], "pairs": ["blkd"], "npairs": ["noisy"], "truth": ["recs"], "conf": ["pairs", "truth"], "nconf": ["npairs", "truth"],
}


def sql(final: str, *steps: str, **other: str) -> str:
    """A statement with the steps that it names and all that those need; `other` replaces or adds steps."""
    order: list[str] = []

    def need(s: str) -> None:
        for x in NEEDS.get(s, []):
            need(x)
        if s not in order:
            order.append(s)

    for s in steps:
        need(s)
    parts = []
    for s in [*order, *[o for o in other if o not in order]]:
        body = other.get(s, STEPS.get(s))
        if body.startswith("PAIRS("):
            body = _pairs(body[6:-1])
        elif body.startswith("CONF("):
            body = _conf(body[5:-1])
        parts.append(f"{s} AS MATERIALIZED ({body})")
    return "WITH " + ",\n".join(parts) + "\n" + final if parts else final


def rate(top: str, bottom: str) -> str:
    return f"round(CASE WHEN {bottom} = 0 THEN 0.0 ELSE ({top}) / ({bottom})::DOUBLE END, 6)"


RATES = f"""SELECT group_id, tp, fp, tn, fn, {rate('fp', '(fp + tn)')} AS fpr, {rate('fn', '(fn + tp)')} AS fnr, {rate('tp', '(tp + fp)')} AS precision,
    {rate('tp', '(tp + fn)')} AS recall, {rate('tp', '(tp + fp + fn)')} AS fstar, {rate('2 * tp', '(2 * tp + fp + fn)')} AS f1"""


# Runs of many scenarios at once, for two groups.


def _erf(x: str) -> str:
    t = f"(1 / (1 + 0.3275911 * abs({x})))"
    a = [f"{c}::DOUBLE" for c in theory.ERF]
    poly = f"{t} * ({a[0]} + {t} * ({a[1]} + {t} * ({a[2]} + {t} * ({a[3]} + {t} * {a[4]}))))"
    return f"(sign({x}) * (1 - ({poly}) * exp(-({x}) * ({x}))))"


def false_match(flip: str) -> str:
    """Chance that a dummy is taken for its source, by the normal law."""
    cut = f"(240.0::DOUBLE * ({flip}) / (2 * (1 - 0.8::DOUBLE) * (1 - ({flip}))) - 150)"
    return f"(CASE WHEN ({flip}) >= 1 THEN 0.0::DOUBLE ELSE 0.5 * (1 - {_erf(f'({cut} / sqrt(150.0::DOUBLE))')}) END)"


def expected_fakes(g: str, x: str) -> str:
    """Fake pairs of a group whose budget is 1 / x."""
    return f"((na{g} + nb{g}) * ({x}) / 2 + bins * ({x}) * ({x}) / 4)"


def group_rate(g: str, x: str, p: str) -> str:
    return f"(({p} * {expected_fakes(g, x)} + fp{g}) / ({expected_fakes(g, x)} + neg{g}))"


def _gap(x: str, p: str) -> str:
    return f"({group_rate('1', x, p)} - {group_rate('2', f'(total - ({x}))', p)})"


def runs_sql(final: str, runs: list, *steps: str, **other: str) -> str:
    """A statement over the counts `cells` (run, scenario, eps, flip, group_id, tp, fp, tn, fn, real, fake) of runs, or over `rcnt`."""
    named = ", ".join(f"({i}, '{r.scenario}', {float(r.eps)}::DOUBLE, {float(r.flip)}::DOUBLE)" for i, r in enumerate(runs))
    p = false_match("flip")
    bisect = f"""
        SELECT * FROM (WITH RECURSIVE b AS (
            SELECT runs.run, runs.flip, two.*, 1 / eps AS total, 1 / (20 * eps) AS least, 0 AS i, 1 / (20 * eps) AS lo, 1 / eps - 1 / (20 * eps) AS hi FROM runs, two WHERE scenario = 'b'
            UNION ALL
            SELECT * REPLACE (i + 1 AS i, CASE WHEN ({_gap('(lo + hi) / 2', p)} < 0) = ({_gap('(total - least)', p)} > {_gap('least', p)}) THEN (lo + hi) / 2 ELSE lo END AS lo,
                CASE WHEN ({_gap('(lo + hi) / 2', p)} < 0) = ({_gap('(total - least)', p)} > {_gap('least', p)}) THEN hi ELSE (lo + hi) / 2 END AS hi) FROM b WHERE i < 80
        ) SELECT run, flip, g1, g2, total, CASE WHEN {_gap('least', p)} * {_gap('(total - least)', p)} > 0
            THEN CASE WHEN abs({_gap('least', p)}) <= abs({_gap('(total - least)', p)}) THEN least ELSE total - least END ELSE (lo + hi) / 2 END AS x FROM b WHERE i = 80)"""
    made = {
        "runs": f"SELECT * FROM (VALUES {named}) t(run, scenario, eps, flip)",
        "gst": """SELECT s.group_id, na, nb, bins, fp, neg, fnr FROM (SELECT group_id, sum(n) FILTER (WHERE party = 'A') AS na, sum(n) FILTER (WHERE party = 'B') AS nb FROM stats GROUP BY group_id) s
            JOIN (SELECT group_id, count(*) FILTER (WHERE sim > 0.8 AND NOT truth) AS fp, count(*) FILTER (WHERE NOT truth) AS neg, count(*) FILTER (WHERE sim <= 0.8 AND truth) / greatest(1, count(*) FILTER (WHERE truth))::DOUBLE AS fnr FROM pairs GROUP BY group_id) c USING (group_id),
            (SELECT count(*) AS bins FROM (SELECT DISTINCT table_no, label FROM stats))""",
        "two": "SELECT a.group_id AS g1, b.group_id AS g2, a.bins, a.na AS na1, a.nb AS nb1, a.fp AS fp1, a.neg AS neg1, b.na AS na2, b.nb AS nb2, b.fp AS fp2, b.neg AS neg2, abs(a.fnr - b.fnr) AS fnr_gap FROM gst a JOIN gst b ON a.group_id < b.group_id",
        "flipped": f"""SELECT run, g1, g2, 2 * eps AS eps, f1, f2 FROM (SELECT *, i / 50.0::DOUBLE AS f1, j / 50.0::DOUBLE AS f2 FROM (SELECT run, eps FROM runs WHERE scenario = 'a'), two, range(51) r1(i), range(51) r2(j))
            QUALIFY row_number() OVER (PARTITION BY run ORDER BY round(greatest(abs({group_rate('1', '1 / (2 * eps)', false_match('f1'))} - {group_rate('2', '1 / (2 * eps)', false_match('f2'))}), fnr_gap), 9), round(abs(f1 - 0.5) + abs(f2 - 0.5), 9), round(abs(f1 - f2), 9), f1, f2) = 1""",
        "shared": bisect,
        "cheap": "SELECT run, flip, g1, g2, total, least(total - least, greatest(least, total / 2 + ((na2 + nb2) / 2.0 - (na1 + nb1) / 2.0) / (4 * (bins / 4.0)))) AS x FROM (SELECT run, flip, 1 / eps AS total, 1 / (20 * eps) AS least FROM runs WHERE scenario = 'cost'), two",
        "kn": """SELECT run, group_id, 2 * eps AS eps, flip FROM runs, (SELECT DISTINCT group_id FROM stats) WHERE scenario = 'b2'
            UNION ALL SELECT run, g1, eps, f1 FROM flipped UNION ALL SELECT run, g2, eps, f2 FROM flipped
            UNION ALL SELECT run, g1, 1 / x, flip FROM (FROM shared UNION ALL FROM cheap) UNION ALL SELECT run, g2, 1 / (total - x), flip FROM (FROM shared UNION ALL FROM cheap)""",
        "rcnt": f"SELECT run, party, table_no, label, group_id, n, flip, least(n, greatest(0, floor({lap(u('noise', 'party', 'table_no', 'label', 'group_id'), f'{DEFAULT.sensitivity} / eps')} + 0.5)))::BIGINT AS m FROM stats JOIN kn USING (group_id)",
        "rk": f"SELECT *, row_number() OVER (PARTITION BY party, table_no, label, group_id ORDER BY md5('{DEFAULT.seed}|pick|' || rec_id || '|' || table_no::VARCHAR)) AS place FROM blk",
        "rch": "SELECT run, flip, rk.* FROM rk JOIN (SELECT * EXCLUDE (n) FROM rcnt WHERE m > 0) c USING (party, table_no, label, group_id) WHERE place <= m",
        "rdm": "SELECT *, (" + ONES + ")::INTEGER AS n_ones FROM (SELECT run, party, rec_id, entity_id, group_id, table_no, label, " + ", ".join(f"{mask(i, 'flip')} AS w{i}" for i in range(5)) + " FROM rch)",
        "rpairs": " UNION ALL ".join(
            f"SELECT {run} AS run, a.group_id, CASE WHEN a.n_ones + b.n_ones = 0 THEN 0.0 ELSE 2.0 * {COMMON} / (a.n_ones + b.n_ones) END AS sim FROM {x} a JOIN {y} b ON a.party = 'A' AND b.party = 'B' AND a.table_no = b.table_no AND a.label = b.label AND a.group_id = b.group_id {more}"
            for run, x, y, more in (("a.run", "rdm", "blk", ""), ("b.run", "blk", "rdm", ""), ("a.run", "rdm", "rdm", "AND a.run = b.run"))
        ),
        "added": "SELECT run, group_id, count(*) FILTER (WHERE sim > 0.8) AS dfp, count(*) FILTER (WHERE sim <= 0.8) AS dtn FROM rpairs GROUP BY ALL",
        "cells": """SELECT run, scenario, eps, flip, c.group_id, tp, fp + coalesce(dfp, 0) AS fp, tn + coalesce(dtn, 0) AS tn, fn, coalesce(o.real, 0) AS real, coalesce(dfp + dtn, 0) AS fake
            FROM runs CROSS JOIN conf c LEFT JOIN (SELECT group_id, count(*) AS real FROM pairs GROUP BY group_id) o USING (group_id) LEFT JOIN added USING (run, group_id)""",
    }
    return sql(final, "conf", "stats", "pairs", "blk", *steps, **(other | made))


SUMMARY = f"""
SELECT scenario, eps, round(fp / greatest(1, fp + tn)::DOUBLE, 6) AS fpr, {rate('tp', '(tp + fn)')} AS recall, {rate('tp', '(tp + fp)')} AS precision, {rate('tp', '(tp + fp + fn)')} AS fstar,
    round(greatest(a, b), 6) AS loss, round(1 - greatest(a, b), 6) AS fairness, comparisons, fake
FROM (SELECT run, scenario, eps, sum(tp) AS tp, sum(fp) AS fp, sum(tn) AS tn, sum(fn) AS fn, (sum(real) + sum(fake))::BIGINT AS comparisons, sum(fake)::BIGINT AS fake,
    max(fp / greatest(1, fp + tn)::DOUBLE) - min(fp / greatest(1, fp + tn)::DOUBLE) AS a, max(fn / greatest(1, fn + tp)::DOUBLE) - min(fn / greatest(1, fn + tp)::DOUBLE) AS b FROM cells GROUP BY run, scenario, eps)"""
