"""DuckDB twins of the selection plans, assembled from common table expressions.

A Twin collects named expressions; each method adds those it needs and returns their names, so that one statement can compare
several methods on one universe.
"""

from __future__ import annotations

import math

from certsel.operators.sampling import POISSON_TERMS
from certsel.operators.thresholds import poisson_one, replicates_for
from certsel.sources.workloads import EMAIL, EXEMPLARS, INSULT, INSULT_PART, NET_CUT, VISIBLE_CUT, WORD
from certsel.spec import NOTHING, SelectionSpec, tail


def _hits(col: str, pattern: str) -> str:
    return f"len(regexp_extract_all({col}, '{pattern}'))"


def _quantised(a: str) -> str:
    return f"CAST(round(1e6 * least(1.0, greatest(0.0, coalesce(({a})::DOUBLE, 0.0)))) AS BIGINT)"


def hashed(key: str, seed: str, stream: str) -> str:
    return f"('0x' || substr(md5(({key})::VARCHAR || ':' || ({seed})::VARCHAR || ':{stream}'), 1, 13))::BIGINT"


def unit(key: str, seed: str, stream: str) -> str:
    return f"(({hashed(key, seed, stream)} + 0.5::DOUBLE) / 4503599627370496::DOUBLE)"


_DOCS = "(SELECT doc_id, coalesce(text, '') AS text, lang, source FROM documents)"
_LABELLED = f"(SELECT d.*, l.quality, l.toxic FROM {_DOCS} d JOIN labels l USING (doc_id))"
LINE_KEY = ("l_orderkey || ':' || l_linenumber || ':' || l_partkey || ':' || l_suppkey || ':' || CAST(round(l_extendedprice * 100) AS BIGINT) || ':' || "
            "strftime(l_shipdate, '%Y-%m-%d')")


def _shingle_sql(table: str, key: str, n: int) -> str:
    return (f"(SELECT DISTINCT {key} AS key, array_to_string(w[i:i + {n - 1}], ' ') AS shingle FROM (SELECT {key}, w, unnest(range(1, len(w) - {n - 2})) AS i FROM "
            f"(SELECT {key}, regexp_extract_all(coalesce(text, ''), '{WORD}') AS w FROM {table}) WHERE len(w) >= {n}))")


def leak_sql(words: int = 3) -> str:
    known = f"(SELECT DISTINCT shingle FROM {_shingle_sql('benchmark', 'item_id', words)})"
    return (f"SELECT doc_id AS key, {_quantised('coalesce(shared, 0) / 20.0')} AS score_u, CAST(EXISTS (SELECT 1 FROM benchmark b WHERE b.text <> '' AND contains(d.text, b.text)) AS INTEGER) AS y "
            f"FROM {_DOCS} d LEFT JOIN (SELECT key, count(*) AS shared FROM {_shingle_sql('documents', 'doc_id', words)} WHERE shingle IN (SELECT shingle FROM {known}) GROUP BY key) s ON d.doc_id = s.key")


def beta_sql(alpha: float, beta: float, seed: int = 0) -> str:
    u = lambda name: unit("key", str(seed), name)
    if beta == 1:
        return f"pow({u('b1')}, {1 / alpha!r}::DOUBLE)"
    if beta == 2:
        return f"pow({u('b1')}, {1 / alpha!r}::DOUBLE) * pow({u('b2')}, {1 / (alpha + 1)!r}::DOUBLE)"
    out = None
    for k in reversed(range(5)):
        x, v = f"pow({u(f'x{k}')}, {1 / alpha!r}::DOUBLE)", f"pow({u(f'v{k}')}, {1 / beta!r}::DOUBLE)"
        out = f"({x} / ({x} + {v}))" if out is None else f"CASE WHEN {x} + {v} <= 1 THEN {x} / ({x} + {v}) ELSE {out} END"
    return out


def synth_sql(alpha: float, beta: float, seed: int = 0, noise: float = 0.0) -> str:
    true = f"SELECT key, {_quantised(beta_sql(alpha, beta, seed))} AS true_u FROM (SELECT {LINE_KEY} AS key FROM lineitem)"
    score = "true_u"
    if noise:
        z = f"sqrt(-2.0::DOUBLE * ln({unit('key', str(seed), 'n1')})) * cos(6.283185307179586::DOUBLE * {unit('key', str(seed), 'n2')})"
        score = _quantised(f"true_u / 1000000::DOUBLE + {noise!r}::DOUBLE * {z}")
    return f"SELECT key, {score} AS score_u, CAST({unit('key', str(seed), 'label')} < true_u / 1000000::DOUBLE AS INTEGER) AS y FROM ({true})"


def _vec_sql(label: int = 3) -> str:
    return f"""SELECT vec_id AS key, {_quantised('(list_inner_product(v, c) / (sqrt(list_inner_product(v, v)) * sqrt(list_inner_product(c, c))) + 1) / 2')} AS score_u,
 CAST(label = {label} AS INTEGER) AS y FROM (SELECT vec_id, label, embedding::DOUBLE[] AS v FROM embeddings) e,
 (SELECT list(m ORDER BY i) AS c FROM (SELECT i, sum(x ORDER BY vec_id) / {EXEMPLARS} AS m FROM (SELECT vec_id, unnest(embedding::DOUBLE[]) AS x, unnest(range(len(embedding))) AS i
   FROM (SELECT * FROM embeddings WHERE label = {label} ORDER BY vec_id LIMIT {EXEMPLARS})) GROUP BY i)) m
 WHERE vec_id NOT IN (SELECT vec_id FROM embeddings WHERE label = {label} ORDER BY vec_id LIMIT {EXEMPLARS})"""


def _bit(c: str) -> str:
    return f"CAST(coalesce({c}, false) AS INTEGER)"


UNIVERSE: dict[str, str] = {
    "pii": f"SELECT doc_id AS key, {_quantised(_hits('text', '[0-9]') + ' / 20.0')} AS score_u, {_bit(f'''regexp_matches(text, '{EMAIL}')''')} AS y FROM {_DOCS}",
    "tox": f"SELECT doc_id AS key, {_quantised(_hits('text', INSULT) + ' / 3.0::DOUBLE')} AS score_u, {_bit('toxic = 1')} AS y FROM {_LABELLED}",
    "junk": f"SELECT doc_id AS key, {_quantised(_hits('text', '[^A-Za-zÀ-ÿ]') + '::DOUBLE / greatest(length(text), 1)')} AS score_u, {_bit('quality = 0')} AS y FROM {_LABELLED}",
    "junk_ascii": f"SELECT doc_id AS key, {_quantised(_hits('text', '[^A-Za-z]') + '::DOUBLE / greatest(length(text), 1)')} AS score_u, {_bit('quality = 0')} AS y, lang FROM {_LABELLED}",
    "audit": f"SELECT doc_id AS key, {_quantised(_hits('text', INSULT_PART) + ' / 2.0')} AS score_u, {_bit(f'''regexp_matches(text, '{INSULT}')''')} AS y FROM {_DOCS} WHERE doc_id NOT IN (SELECT doc_id FROM labels WHERE doc_id IS NOT NULL)",
    "leak": leak_sql(),
    "rare": f"SELECT event_id AS key, {_quantised('value / 300')} AS score_u, {_bit('''event_type = 'purchase' AND value > 200''')} AS y FROM events",
    "net": f"SELECT {LINE_KEY} AS key, {_quantised(f'l_extendedprice / {NET_CUT}::DOUBLE')} AS score_u, {_bit(f'l_extendedprice * (1 - l_discount) * (1 + l_tax) > {NET_CUT}')} AS y, year(l_shipdate) AS part FROM lineitem",
    "bulk": f"SELECT o_orderkey AS key, {_quantised('coalesce(n, 0) / 20.0')} AS score_u, {_bit('qty > 250')} AS y FROM orders LEFT JOIN (SELECT l_orderkey, count(*) AS n, sum(l_quantity) AS qty FROM lineitem GROUP BY 1) ON o_orderkey = l_orderkey",
    "chat": f"SELECT conv_id || ':' || turn AS key, {_quantised('length(text) / 2000.0')} AS score_u, {_bit('''role = 'assistant' ''')} AS y FROM conversations",
    "vec": _vec_sql(),
    "page": f"SELECT page_id AS key, {_quantised(_hits(f'''regexp_replace(coalesce(html, ''), '{VISIBLE_CUT}', '', 'g')''', '[0-9]') + ' / 40.0')} AS score_u, {_bit(f'''regexp_matches(html, '{EMAIL}')''')} AS y FROM pages",
}


class Twin:
    def __init__(self, universe: str):
        self.parts: list[tuple[str, str]] = [("u", universe)]
        self.n = 0

    def add(self, sql: str, name: str | None = None) -> str:
        """The name of an expression; one that is there already is used again."""
        known = {text: n for n, text in self.parts[1:]}
        if sql in known and not name:
            return known[sql]
        self.n += 1
        name = name or f"q{self.n}"
        self.parts.append((name, sql))
        return name

    def done(self, final: str) -> str:
        return "WITH " + ",\n".join(f"{n} AS MATERIALIZED ({s})" for n, s in self.parts) + f"\n{final}"

    # samples: trial, key, score_u, y, mult, r_u
    def uniform_distinct(self, budget: int, trials: int = 1, seed: int = 0) -> str:
        share = budget + 10 * math.sqrt(budget) + 50
        n = self.add(f"SELECT greatest(1, floor(count(*) / {share!r}::DOUBLE))::INTEGER AS parts FROM u")
        return self.add(f"""SELECT trial, key, score_u, y, 1::BIGINT AS mult, 1000000::BIGINT AS r_u FROM (
 SELECT *, row_number() OVER (PARTITION BY trial ORDER BY h, key) AS k FROM (SELECT *, (block * parts + floor(h / 4503599627370496::DOUBLE * parts))::INTEGER AS trial FROM (
 SELECT key, score_u, y, parts, block, {hashed('key', f'block + {seed}', 'uniform')} AS h FROM u, (SELECT parts, unnest(range((({trials} - 1) // parts) + 1))::INTEGER AS block FROM {n}))) WHERE trial < {trials}) WHERE k <= {budget}""")

    def weights(self, source: str, exponent: float = 0.5, mix: float = 0.1, by_trial: bool = False) -> str:
        t, over = ("trial, ", "PARTITION BY trial") if by_trial else ("", "")
        p = f"CAST(round(1000000::DOUBLE * pow(score_u / 1000000::DOUBLE, {float(exponent)!r}::DOUBLE)) AS BIGINT)"
        share = f"CASE WHEN pt > 0 THEN {float(mix)!r}::DOUBLE + {1.0 - mix!r}::DOUBLE * n * p_u / pt ELSE 1.0::DOUBLE END"
        return self.add(f"""SELECT {t}key, score_u, y, p_u, n, CAST(round(1000000000::DOUBLE * ({share})) AS BIGINT) AS w_u FROM (
 SELECT {t}key, score_u, y, p_u, count(*) OVER ({over}) AS n, sum(p_u) OVER ({over})::BIGINT AS pt FROM (SELECT {t}key, score_u, y, {p} AS p_u FROM {source}))""")

    def weighted_cdf(self, budget: int, trials: int = 1, seed: int = 0, exponent: float = 0.5, mix: float = 0.1, source: str = "u", by_trial: bool = False, stream: str = "draw") -> str:
        w = self.weights(source, exponent, mix, by_trial)
        t, part = ("trial, ", "PARTITION BY trial") if by_trial else ("", "")
        h = f"substr(md5(key::VARCHAR || ':{seed}:order'), 1, 13)"
        run = self.add(f"""SELECT {t}key, score_u, y, w_u, n, sum(w_u) OVER ({part} ORDER BY score_u, h, key ROWS UNBOUNDED PRECEDING)::BIGINT AS e, sum(w_u) OVER ({part})::BIGINT AS total
 FROM (SELECT *, {h} AS h FROM {w})""")
        totals = f"(SELECT DISTINCT {t}total FROM {run})"
        on = "d.trial = t.trial" if by_trial else "true"
        draws = f"""(SELECT d.trial, CAST(floor(du * total) AS BIGINT) AS at FROM (SELECT trial, {unit('j', f'trial + {seed}', stream)} AS du FROM
 (SELECT unnest(range({trials}))::INTEGER AS trial), (SELECT unnest(range({budget})) AS j)) d JOIN {totals} t ON {on})"""
        j = "d.trial = r.trial AND " if by_trial else ""
        return self.add(f"""SELECT d.trial, key, score_u, y, count(*) AS mult, CAST(round(1000000::DOUBLE * total / (n * w_u)) AS BIGINT) AS r_u
 FROM {draws} d ASOF JOIN (SELECT *, e - w_u AS st FROM {run} WHERE w_u > 0) r ON {j}d.at >= r.st GROUP BY d.trial, key, score_u, y, total, n, w_u""")

    def curves(self, sample: str) -> str:
        b = self.add(f"""SELECT trial, score_u, sum(mult)::BIGINT AS d, sum(mult * r_u)::BIGINT AS c, sum(mult * r_u * y)::BIGINT AS cy, sum((mult * r_u * r_u)::HUGEINT) AS c2, sum((mult * r_u * r_u * y)::HUGEINT) AS cy2
 FROM {sample} GROUP BY trial, score_u""")
        w = "(PARTITION BY trial ORDER BY score_u DESC ROWS UNBOUNDED PRECEDING)"
        return self.add(f"""SELECT trial, score_u, d, sum(d) OVER {w}::BIGINT AS k, sum(c) OVER {w}::BIGINT AS cum_all, sum(cy) OVER {w}::BIGINT AS cum_pos, sum(c2) OVER {w} AS sq_all, sum(cy2) OVER {w} AS sq_pos,
 sum(cy) OVER (PARTITION BY trial)::BIGINT AS total_pos FROM {b}""")

    def _result(self, sample: str, tau: str, default: int, target: float, missing: str) -> str:
        return self.add(f"""SELECT l.trial, coalesce(tau_u, {default})::BIGINT AS tau_u, coalesce(target_u, {round(target * 1e6)})::BIGINT AS target_u, n_labels,
 CASE WHEN tau_u IS NULL THEN '{missing}' ELSE flag END AS flag
 FROM (SELECT trial, count(*) AS n_labels FROM {sample} GROUP BY trial) l LEFT JOIN {tau} t ON l.trial = t.trial""")

    def raw_recall(self, sample: str, target: float) -> str:
        c = self.curves(sample)
        t = self.add(f"SELECT trial, max(score_u) AS tau_u, NULL AS target_u, 'unguaranteed' AS flag FROM {c} WHERE total_pos > 0 AND cum_pos::DOUBLE >= {target!r}::DOUBLE * total_pos::DOUBLE GROUP BY trial")
        return self._result(sample, t, 0, target, 'no_match')

    def raw_precision(self, sample: str, target: float) -> str:
        c = self.curves(sample)
        t = self.add(f"SELECT trial, min(score_u) AS tau_u, NULL AS target_u, 'unguaranteed' AS flag FROM {c} WHERE cum_pos::DOUBLE >= {target!r}::DOUBLE * cum_all::DOUBLE GROUP BY trial")
        return self._result(sample, t, NOTHING, target, 'none_passed')

    def bound_recall(self, sample: str, s: SelectionSpec, r_max: float = 1.0) -> str:
        c, g, half = self.curves(sample), s.target, s.delta / 2
        first = self.add(f"SELECT trial, max(score_u) AS t0 FROM {c} WHERE total_pos > 0 AND cum_pos::DOUBLE >= {g!r}::DOUBLE * total_pos::DOUBLE GROUP BY trial")
        v, v2 = "mult * r_u * y", "(mult * r_u * r_u * y)::HUGEINT"
        h = self.add(f"""SELECT s.trial, sum(mult)::DOUBLE AS s, sum(CASE WHEN score_u >= t0 THEN {v} ELSE 0 END)::DOUBLE AS a1, sum(CASE WHEN score_u >= t0 THEN {v2} ELSE 0 END)::DOUBLE AS a2,
 sum(CASE WHEN score_u >= t0 THEN 0 ELSE {v} END)::DOUBLE AS b1, sum(CASE WHEN score_u >= t0 THEN 0 ELSE {v2} END)::DOUBLE AS b2 FROM {sample} s JOIN {first} f ON s.trial = f.trial GROUP BY s.trial""")
        bounds = {"top": f"a1 / s + sqrt(greatest(0.0::DOUBLE, (a2 - a1 * a1 / s) / (s - 1.0::DOUBLE))) / sqrt(s) * {tail(half)!r}::DOUBLE",
                  "bottom": f"b1 / s - sqrt(greatest(0.0::DOUBLE, (b2 - b1 * b1 / s) / (s - 1.0::DOUBLE))) / sqrt(s) * {tail(half)!r}::DOUBLE"}
        if s.bound == "hoeffding":
            wide = f"{1e6 * r_max * math.sqrt(math.log(1 / half) / 2)!r}::DOUBLE / sqrt(s)"
            bounds = {"top": f"a1 / s + {wide}", "bottom": f"b1 / s - {wide}"}
        elif s.bound == "bootstrap":
            means = self.add(f"""SELECT r.trial, rep, sum(CASE WHEN score_u >= t0 THEN m * r_u * y ELSE 0 END)::DOUBLE / sum(m) AS above,
 sum(CASE WHEN score_u >= t0 THEN 0 ELSE m * r_u * y END)::DOUBLE / sum(m) AS below FROM {self.replicated(sample, replicates_for(half), s.seed)} r JOIN {first} f ON r.trial = f.trial GROUP BY r.trial, rep""")
            h = self.add(f"""SELECT h.*, top, bottom FROM {h} h JOIN (SELECT trial, quantile_cont(above, {1 - half!r}) AS top, quantile_cont(below, {half!r}) AS bottom FROM {means} GROUP BY trial) q ON h.trial = q.trial""")
            bounds = {"top": "top", "bottom": "bottom"}
        goal = self.add(f"""SELECT trial, least(1.0::DOUBLE, hi / (hi + greatest(0.0::DOUBLE, lo))) AS goal, lo <= 0 AS over, pow({g!r}::DOUBLE, (a1 + b1) * (a1 + b1) / (a2 + b2)) <= {s.delta!r}::DOUBLE AS enough
 FROM (SELECT *, {bounds['top']} AS hi, {bounds['bottom']} AS lo FROM {h})""")
        cut = "CASE WHEN bool_or(over AND NOT enough) THEN 0 ELSE max(score_u) END" if s.overflow == "guarded" else "max(score_u)"
        t = self.add(f"""SELECT c.trial, {cut} AS tau_u, max(round(goal * 1000000::DOUBLE)) AS target_u, CASE WHEN bool_or(over AND NOT enough) THEN 'few_matches' WHEN bool_or(over) THEN 'clamped' ELSE '' END AS flag
 FROM {c} c JOIN {goal} g ON c.trial = g.trial WHERE total_pos > 0 AND cum_pos::DOUBLE >= goal * total_pos::DOUBLE GROUP BY c.trial""")
        return self._result(sample, t, 0, g, "no_match")

    def copies(self, source: str, u: str, rate: str) -> str:
        """source with copies, the Poisson count of its uniform number u at its rate."""
        e = self.add(f"SELECT *, row_number() OVER () AS rid, {u} AS pu, {rate} AS pr FROM {source}")
        # All terms of all rows; sums run in the order of the terms.
        c = self.add(f"SELECT rid, count(*) AS copies FROM (SELECT rid, pu, sum(exp(-pr) * pow(pr, i) / gamma(i + 1.0::DOUBLE)) OVER (PARTITION BY rid ORDER BY i ROWS UNBOUNDED PRECEDING) AS c "
                     f"FROM {e}, (SELECT unnest(range({POISSON_TERMS} + 1)) AS i) WHERE pu > exp(-pr)) WHERE pu > c GROUP BY rid")
        return self.add(f"SELECT e.*, coalesce(copies, 0) AS copies FROM {e} e LEFT JOIN {c} c ON e.rid = c.rid")

    def replicated(self, sample: str, replicates: int, seed: int) -> str:
        u = self.add(f"SELECT trial, key, score_u, y, r_u, rep, {unit("key || '/' || trial || '/' || draw", f'rep + {seed}', 'boot')} AS pu FROM (SELECT *, unnest(range(1, mult + 1)) AS draw FROM {sample}), "
                     f"(SELECT unnest(range({replicates}))::INTEGER AS rep)")
        m = " + ".join(f"(pu > {c!r}::DOUBLE)::INTEGER" for c in poisson_one())
        return self.add(f"SELECT * FROM (SELECT *, {m} AS m FROM {u}) WHERE m > 0")

    def poisson(self, budget: int, seed: int = 0, exponent: float = 0.5, mix: float = 0.1) -> str:
        w = self.weights("u", exponent, mix)
        rate = budget + 5 * math.sqrt(budget) + 20
        r = self.add(f"SELECT *, {rate!r}::DOUBLE * w_u / total AS rate, greatest(1, ceil({rate!r}::DOUBLE * w_u / total / 15)::INTEGER) AS pieces FROM {w}, (SELECT sum(w_u)::BIGINT AS total FROM {w})")
        p = self.add(f"SELECT *, unnest(range(1, pieces + 1)) AS piece FROM {r}")
        c = self.copies(p, unit("key || '/' || piece", str(seed), "poisson"), "rate / pieces")
        k = self.add(f"SELECT *, unnest(range(1, copies + 1)) AS copy FROM {c} WHERE copies > 0")
        h2 = hashed("key || '/' || piece || '/' || copy", str(seed), "keep")
        return self.add(f"""SELECT 0 AS trial, key, score_u, y, count(*) AS mult, r_u FROM (SELECT key, score_u, y, CAST(round(1000000::DOUBLE * total / (n * w_u)) AS BIGINT) AS r_u
 FROM {k} ORDER BY {h2}, key LIMIT {budget}) GROUP BY key, score_u, y, r_u""")

    def bound_precision(self, sample: str, s: SelectionSpec, share: float) -> str:
        c = self.curves(sample)
        p = self.add(f"SELECT *, cum_pos::DOUBLE / cum_all::DOUBLE AS p, cum_all::DOUBLE / k::DOUBLE AS mr FROM {c} WHERE k // {s.step} > (k - d) // {s.step}")
        sd = self.add(f"SELECT *, CASE WHEN k > 1 THEN sqrt(greatest(0.0::DOUBLE, (sq_pos::DOUBLE * (1.0::DOUBLE - p - p) + sq_all::DOUBLE * p * p) / (mr * mr) / (k - 1)::DOUBLE)) ELSE 0.0::DOUBLE END AS sd FROM {p}")
        if s.bound == "bootstrap":
            r = self.add(f"""SELECT trial, rep, score_u, sum(m * r_u)::BIGINT AS c, sum(m * r_u * y)::BIGINT AS cy FROM {self.replicated(sample, replicates_for(share), s.seed)} GROUP BY trial, rep, score_u""")
            w = "(PARTITION BY e.trial, e.rep ORDER BY e.score_u DESC ROWS UNBOUNDED PRECEDING)"
            down = self.add(f"""SELECT e.trial, e.score_u, sum(c) OVER {w} AS c, sum(cy) OVER {w} AS cy FROM (SELECT trial, score_u, unnest(range({replicates_for(share)}))::INTEGER AS rep FROM (SELECT DISTINCT trial, score_u FROM {sample})) e
 LEFT JOIN {r} r ON e.trial = r.trial AND e.rep = r.rep AND e.score_u = r.score_u""")
            low = self.add(f"SELECT trial, score_u, quantile_cont(coalesce(cy::DOUBLE / c::DOUBLE, 0.0::DOUBLE), {share!r}) AS low FROM {down} GROUP BY trial, score_u")
            passed = f"{sd} d JOIN {low} l ON d.trial = l.trial AND d.score_u = l.score_u WHERE low > {s.target!r}::DOUBLE"
        else:
            passed = f"{sd} d WHERE p - sd / sqrt(k::DOUBLE) * {tail(share)!r}::DOUBLE > {s.target!r}::DOUBLE"
        t = self.add(f"SELECT d.trial, min(d.score_u) AS tau_u, NULL AS target_u, '' AS flag FROM {passed} GROUP BY d.trial")
        return self._result(sample, t, NOTHING, s.target, "none_passed")

    def twostage(self, s: SelectionSpec, trials: int = 1) -> tuple[str, str]:
        half = s.budget // 2
        one = self.weighted_cdf(half, trials, s.seed, s.exponent, s.mix, stream="stage1")
        v, v2 = "mult * r_u * y", "(mult * r_u * r_u * y)::HUGEINT"
        m = self.add(f"SELECT trial, sum(mult)::DOUBLE AS s, sum({v})::DOUBLE AS a1, sum({v2})::DOUBLE AS a2, (SELECT count(*) FROM u) AS n FROM {one} GROUP BY trial")
        sd = "sqrt(greatest(0.0::DOUBLE, (a2 - a1 * a1 / s) / (s - 1.0::DOUBLE))) / 1000000::DOUBLE"
        rank = self.add(f"SELECT trial, n, CAST(ceil(least(n::DOUBLE, n * (a1 / s / 1000000::DOUBLE + {sd} / sqrt(s) * {tail(s.delta / 2)!r}::DOUBLE)) / {s.target!r}::DOUBLE) AS BIGINT) AS rank FROM {m}")
        down = self.add("SELECT score_u, sum(count(*)) OVER (ORDER BY score_u DESC ROWS UNBOUNDED PRECEDING)::BIGINT AS cum FROM u GROUP BY score_u")
        floor = self.add(f"SELECT r.trial, coalesce((SELECT max(score_u) FROM {down} d WHERE d.cum >= r.rank AND r.rank < r.n), 0) AS floor FROM {rank} r")
        region = self.add(f"SELECT f.trial, key, score_u, y FROM u JOIN {floor} f ON score_u >= floor")
        two = self.weighted_cdf(half, trials, s.seed, s.exponent, s.mix, region, True, "stage2")
        used = two if s.stage2_weighting == "ratio" else self.add(f"SELECT trial, key, score_u, y, mult, 1000000::BIGINT AS r_u FROM {two}")
        terms = s.grid_tests if s.union_terms == "budget" else max(1, math.ceil(half / s.step))
        tau = self.bound_precision(used, s, s.delta / (2 * terms))
        both = self.add(f"SELECT DISTINCT trial, key, score_u, y FROM (SELECT trial, key, score_u, y FROM {one} UNION ALL SELECT trial, key, score_u, y FROM {two})")
        out = self.add(f"""SELECT l.trial, coalesce(tau_u, {NOTHING})::BIGINT AS tau_u, {round(s.target * 1e6)}::BIGINT AS target_u, l.n_labels, coalesce(flag, 'none_passed') AS flag FROM (SELECT trial, count(*) AS n_labels FROM {both} GROUP BY trial) l
 LEFT JOIN {tau} t ON l.trial = t.trial""")
        return out, both

    def estimate(self, s: SelectionSpec, trials: int = 1) -> tuple[str, str]:
        """Names of (cut-offs, labelled rows)."""
        if s.method == "twostage":
            return self.twostage(s, trials)
        if s.method in ("weighted", "onestage"):
            sample, r_max = self.weighted_cdf(s.budget, trials, s.seed, s.exponent, s.mix), 1 / s.mix if s.mix else 1e6
        elif s.draws == "iid":
            sample, r_max = self.weighted_cdf(s.budget, trials, s.seed, 0.0, 1.0, stream="iid"), 1.0
        else:
            sample, r_max = self.uniform_distinct(s.budget, trials, s.seed), 1.0
        if s.method == "uniform_raw":
            return (self.raw_recall if s.goal == "recall" else self.raw_precision)(sample, s.target), sample
        if s.goal == "recall":
            return self.bound_recall(sample, s, r_max), sample
        terms = s.grid_tests if s.union_terms == "budget" else max(1, math.ceil(s.budget / s.step))
        return self.bound_precision(sample, s, s.delta / terms), sample

    def achieved(self, tau: str, labelled: str, hist: str = "u") -> str:
        return self.add(f"""SELECT *, CASE WHEN size > 0 THEN hits / size ELSE 1.0 END AS precision, CASE WHEN matches > 0 THEN hits / matches ELSE 1.0 END AS recall FROM (
 SELECT t.trial, t.tau_u, (SELECT count(*) FROM {hist} WHERE score_u >= t.tau_u) + coalesce(x.extra, 0) AS size, (SELECT coalesce(sum(y), 0)::BIGINT FROM {hist} WHERE score_u >= t.tau_u) + coalesce(x.extra, 0) AS hits,
 (SELECT sum(y)::BIGINT FROM {hist}) AS matches FROM {tau} t LEFT JOIN (SELECT l.trial, count(DISTINCT key) AS extra FROM {labelled} l JOIN {tau} t ON l.trial = t.trial WHERE y = 1 AND score_u < tau_u GROUP BY l.trial) x ON t.trial = x.trial)""")

    def failure(self, name: str, s: SelectionSpec, trials: int, extra: str = "") -> str:
        m = self.achieved(*self.estimate(s, trials))
        other = "precision" if s.goal == "recall" else "recall"
        return f"""SELECT {extra}'{name}' AS method, {s.target!r}::DOUBLE AS target, count(*) AS n_trials, sum(({s.goal} < {s.target!r}::DOUBLE)::INTEGER)::BIGINT AS n_failed, round(avg(({s.goal} < {s.target!r}::DOUBLE)::INTEGER), 6) AS failure_rate,
 round(avg({other}), 6) AS quality, round(avg(size), 6) AS mean_size FROM {m}"""

    def answer(self, s: SelectionSpec) -> str:
        tau, labelled = self.estimate(s)
        drop = f" AND key NOT IN (SELECT key FROM {labelled} WHERE y = 0)" if s.drop_known_negatives else ""
        whole = f"(SELECT count(*) FROM u) <= {s.budget}"
        return f"SELECT key, score_u FROM u WHERE CASE WHEN {whole} THEN y = 1 ELSE (score_u >= (SELECT tau_u FROM {tau}) OR key IN (SELECT key FROM {labelled} WHERE y = 1)){drop} END"
