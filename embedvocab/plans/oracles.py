"""What each query must return, by definition, in plain SQL over the whole tables."""

from __future__ import annotations

from itertools import permutations

ORACLES: dict[str, str] = {}

# ---------------------------------------------------------------- corpora

_DOCS = r"""docs AS (SELECT doc_id, lang, source, text, regexp_extract_all(lower(coalesce(text, '')), '\p{L}+') AS ws FROM documents)"""
_EACH = "each AS (SELECT doc_id, lang, source, unnest(ws) AS lemma, unnest(range(len(ws))) AS i FROM docs)"
_EN = f"""{_DOCS}, {_EACH}, words AS (SELECT 'en' AS corpus_id, doc_id, i, lemma, row_number() OVER (ORDER BY doc_id, i) - 1 AS pos FROM each WHERE lang = 'en')"""
_STATS = """freq AS (SELECT corpus_id, lemma, count(*) AS n FROM words GROUP BY ALL),
ranked AS (SELECT corpus_id, lemma, n, row_number() OVER o AS rank, coalesce(sum(n) OVER (o ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS before, sum(n) OVER (PARTITION BY corpus_id) AS total
  FROM freq WINDOW o AS (PARTITION BY corpus_id ORDER BY n DESC, lemma)),
gap AS (SELECT corpus_id, lemma, pos - lag(pos) OVER (PARTITION BY corpus_id, lemma ORDER BY pos) AS g FROM words),
days AS (SELECT corpus_id, lemma, quantile_cont(g, 0.9) / 36000.0 AS d FROM gap WHERE g IS NOT NULL GROUP BY ALL)"""


def _cells(alphas: tuple[float, ...]) -> str:
    rows = ", ".join(f"({a}::DOUBLE, {round(a * 1000)})" for a in alphas)
    return f"cells AS (SELECT r.corpus_id, a.alpha, count(*) AS vocab, count(d) AS lemmas_with_gap, quantile_cont(d, 0.9) AS days FROM ranked r JOIN (VALUES {rows}) a(alpha, share) ON r.before * 1000 < r.total * a.share LEFT JOIN days USING (corpus_id, lemma) GROUP BY ALL)"


_ALPHAS = (0.5, 0.6, 0.7, 0.8, 0.9)
_CELL_ROWS = "SELECT corpus_id, alpha, vocab, lemmas_with_gap, round(days, 6) AS revisit_days FROM cells"
ORACLES["corpus_revisit_en"] = f"WITH {_EN}, {_STATS}, {_cells((0.5, 0.7, 0.8, 0.9))} {_CELL_ROWS}"
_BY = "{}, {}, words AS (SELECT {} AS corpus_id, doc_id, i, lemma, row_number() OVER (PARTITION BY {} ORDER BY doc_id, i) - 1 AS pos FROM each WHERE {})"
_STEM = r"""CASE WHEN regexp_matches(lemma, 'ies$') AND NOT regexp_matches(lemma, '[ea]ies$') THEN regexp_replace(lemma, 'ies$', 'y')
  WHEN regexp_matches(lemma, 'es$') AND NOT regexp_matches(lemma, '[aeo]es$') THEN regexp_replace(lemma, 'es$', 'e')
  WHEN regexp_matches(lemma, 's$') AND NOT regexp_matches(lemma, '[us]s$') THEN regexp_replace(lemma, 's$', '') ELSE lemma END"""
ORACLES["corpus_revisit_s_stem"] = f"WITH {_EN.replace('lemma, row_number()', f'{_STEM} AS lemma, row_number()')}, {_STATS}, {_cells((0.5, 0.7, 0.8, 0.9))} {_CELL_ROWS}"
_FORMS = f"forms AS (SELECT lemma AS word, {_STEM} AS stem FROM (SELECT DISTINCT lemma FROM each WHERE lang = 'en')), dic AS (SELECT word, stem FROM forms WHERE word <> stem AND stem IN (SELECT word FROM forms))"
ORACLES["corpus_revisit_dictionary"] = f"WITH {_EN.replace('words AS (', _FORMS + ', plain AS (')}, words AS (SELECT corpus_id, doc_id, pos, coalesce(stem, lemma) AS lemma FROM plain LEFT JOIN dic ON word = lemma), {_STATS}, {_cells((0.5, 0.7, 0.8, 0.9))} {_CELL_ROWS}"
ORACLES["corpus_revisit_by_lang"] = f"WITH {_BY.format(_DOCS, _EACH, 'lang', 'lang', 'true')}, {_STATS}, {_cells(_ALPHAS)} {_CELL_ROWS}"
ORACLES["author_revisit"] = f"WITH {_BY.format(_DOCS, _EACH, 'source', 'source', chr(39).join(['lang = ', 'en', '']))}, {_STATS}, {_cells((0.9,))} {_CELL_ROWS}"
ORACLES["corpus_revisit_sketched"] = f"WITH {_EN}, {_STATS}, {_cells((0.5, 0.9))} SELECT corpus_id, alpha, round(days, 6) AS revisit_days, true AS near FROM cells"
ORACLES["vocabulary_sketched"] = f"WITH {_DOCS}, {_EACH} SELECT lang AS corpus_id, count(DISTINCT lemma) AS vocab, true AS near FROM each GROUP BY 1"
ORACLES["lemma_top_sketched"] = f"WITH {_DOCS}, {_EACH}, nn AS (SELECT lang AS corpus_id, lemma, count(*) AS n FROM each GROUP BY lang, lemma QUALIFY row_number() OVER (PARTITION BY lang ORDER BY count(*) DESC, lemma) <= 20) SELECT corpus_id, sum(n)::BIGINT AS uses, true AS near FROM nn GROUP BY 1"
ORACLES["lemma_revisit_top"] = f"WITH {_EN}, {_STATS} SELECT lemma, n, rank, round(d, 6) AS revisit_days FROM ranked LEFT JOIN days USING (corpus_id, lemma) WHERE rank <= 100"
ORACLES["corpus_gap_histogram"] = f"WITH {_EN}, {_STATS} SELECT floor(g / 36000.0)::INTEGER AS day_bucket, count(*) AS gaps FROM gap WHERE g IS NOT NULL GROUP BY 1"
ORACLES["corpus_gaps_between"] = f"WITH {_EN}, {_STATS} SELECT corpus_id, count(*) AS gaps, sum(g - 1)::BIGINT AS words_between FROM gap WHERE g IS NOT NULL GROUP BY 1"
ORACLES["revisit_speed_sensitivity"] = f"WITH {_EN}, {_STATS}, {_cells((0.9,))} SELECT wpm, hours, round(days * 600 / (wpm * hours), 6) AS revisit_days FROM cells, (VALUES (100), (200), (300), (400)) a(wpm), (VALUES (1), (3), (5)) b(hours)"
_BOOKS = f"""{_DOCS}, {_EACH}, books AS (SELECT doc_id, source AS author, len(ws) AS n_words FROM docs WHERE lang = 'en' AND len(ws) >= 1000),
words AS (SELECT doc_id AS corpus_id, i AS pos, lemma FROM each SEMI JOIN books USING (doc_id))"""
ORACLES["book_revisit"] = f"WITH {_BOOKS}, {_STATS}, {_cells((0.9,))} SELECT doc_id, author, n_words::INTEGER AS n_words, vocab, round(days, 6) AS revisit_days FROM books JOIN cells ON doc_id = corpus_id"
ORACLES["book_vocab"] = f"WITH {_BOOKS}, {_STATS}, {_cells((0.9,))} SELECT doc_id, author, n_words::INTEGER AS n_words, vocab FROM books JOIN cells ON doc_id = corpus_id"
_Q = "round(quantile_cont({0}, 0.25), 6) AS q1, round(quantile_cont({0}, 0.5), 6) AS median, round(quantile_cont({0}, 0.75), 6) AS q3"
ORACLES["book_revisit_summary"] = f"WITH {_BOOKS}, {_STATS}, {_cells((0.9,))} SELECT count(days) AS n_books, {_Q.format('days')}, count(DISTINCT author) AS n_authors FROM books JOIN cells ON doc_id = corpus_id"
ORACLES["book_length_stats"] = f"WITH {_BOOKS} SELECT count(*) AS n_books, {_Q.format('n_words')}, count(DISTINCT author) AS n_authors FROM books"

# ---------------------------------------------------------------- browsing


def _draw(*keys: str) -> str:
    return f"('0x' || substr(md5(concat_ws('|', {', '.join(keys)})), 1, 8))::BIGINT / 4294967296.0"


_EVENTS = "ev AS (SELECT event_id, user_id, ts, event_type, value, json_extract(props, '$.k')::INTEGER AS k FROM events)"
_PAGES = """np AS (SELECT count(*) AS n FROM pages),
page_ws AS (SELECT page_id::INTEGER AS u, regexp_extract_all(lower(regexp_replace(regexp_replace(regexp_extract(html, '(?s)<article>(.*)</article>', 1), '<[^>]+>', ' ', 'g'), '&[a-z]+;', ' ', 'g')), '\\p{L}+') AS ws FROM pages)""".replace("\\\\", "\\")
_CLICKS = f"""{_EVENTS}, {_PAGES},
st AS (SELECT event_id, user_id, ts, (((user_id % greatest(1, (n + 99) // 100)) * 100 + k % least(100, n)) % n)::INTEGER AS u FROM ev, np),
nx AS (SELECT u, CASE WHEN date_diff('microsecond', ts, lead(ts) OVER q) <= 43200000000 THEN lead(u) OVER q END AS v FROM st WINDOW q AS (PARTITION BY user_id ORDER BY ts, event_id)),
ed AS (SELECT u, v, count(*) AS n FROM nx GROUP BY ALL),
tr AS (SELECT u, v, (sum(n) OVER (PARTITION BY u ORDER BY v NULLS LAST) - n) / sum(n) OVER (PARTITION BY u) AS lo, sum(n) OVER (PARTITION BY u ORDER BY v NULLS LAST) / sum(n) OVER (PARTITION BY u) AS hi FROM ed),
vs AS (SELECT u, sum(n) AS n FROM ed GROUP BY u),
sp AS (SELECT u, (sum(n) OVER (ORDER BY u) - n) / sum(n) OVER () AS lo, sum(n) OVER (ORDER BY u) / sum(n) OVER () AS hi FROM vs)"""
ORACLES["click_transitions"] = f"WITH {_CLICKS} SELECT u, v, round(lo, 6) AS lo, round(hi, 6) AS hi FROM tr"
ORACLES["click_starts"] = f"WITH {_CLICKS} SELECT u, round(lo, 6) AS lo, round(hi, 6) AS hi FROM sp"


def _browsed(limits: str) -> str:
    """Each session page by page: a stop jumps back to the start, and the session ends once its words exceed the limit.

    A session that ends has more words than the limit, so total // limit + 1 of them reach the total, besides those that start at a sink.
    """
    return f"""{_CLICKS},
lim AS (SELECT l AS corpus_id, 800 * n AS total FROM (VALUES {limits}) v(l), np),
ses AS (SELECT corpus_id, total, unnest(range(total // corpus_id + 20)) AS s FROM lim),
len AS (SELECT u, len(ws) AS n FROM page_ws),
sink AS (SELECT u FROM ed GROUP BY u HAVING count(v) = 0),
beg AS (SELECT corpus_id, s, sp.u, coalesce(len.n, 0) AS n FROM (SELECT *, {_draw("'42'", "'s'", 'corpus_id', 's')} AS x FROM ses) JOIN sp ON lo <= x AND x < hi LEFT JOIN len ON len.u = sp.u),
wk AS (SELECT corpus_id, s, 0 AS w, 0 AS step, u, u AS u0, n, n AS so_far, u IN (SELECT u FROM sink) AS ended FROM beg
  UNION ALL SELECT y.corpus_id, y.s, CASE WHEN tr.v IS NULL THEN y.w + 1 ELSE y.w END, CASE WHEN tr.v IS NULL THEN 0 ELSE y.step + 1 END, coalesce(tr.v, y.u0), y.u0, coalesce(len.n, 0), y.so_far + coalesce(len.n, 0), false
  FROM (SELECT *, {_draw("'42'", "'w'", 'corpus_id', 's', 'w', 'step + 1')} AS x FROM wk WHERE so_far <= corpus_id AND NOT ended) y JOIN tr ON tr.u = y.u AND lo <= x AND x < hi LEFT JOIN len ON len.u = tr.v),
kp AS (SELECT corpus_id, s, w, step, u, n FROM wk WHERE step > 0 OR w = 0),
sz AS (SELECT corpus_id, s, sum(n) AS n FROM kp GROUP BY ALL),
ah AS (SELECT corpus_id, s, coalesce(sum(n) OVER (PARTITION BY corpus_id ORDER BY s ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS ahead FROM sz),
rd AS (SELECT kp.* FROM kp JOIN ah USING (corpus_id, s) JOIN lim USING (corpus_id) WHERE ahead < lim.total),
ex AS (SELECT corpus_id, s, w, step, unnest(ws) AS lemma, unnest(range(len(ws))) AS i FROM rd JOIN page_ws USING (u)),
words AS (SELECT corpus_id, lemma, row_number() OVER (PARTITION BY corpus_id ORDER BY s, w, step, i) - 1 AS pos FROM ex)"""


_LIMITS = "(100), (1000), (10000), (100000)"
ORACLES["browse_sessions"] = f"WITH RECURSIVE {_browsed(_LIMITS)} SELECT corpus_id AS session_words, s::INTEGER AS s, w::INTEGER AS w, step, u, n FROM rd"
ORACLES["browse_revisit_grid"] = f"WITH RECURSIVE {_browsed(_LIMITS)}, {_STATS}, {_cells(_ALPHAS)} SELECT corpus_id AS session_words, alpha, vocab, lemmas_with_gap, round(days, 6) AS revisit_days FROM cells"
ORACLES["browse_vocab_by_alpha"] = f"WITH RECURSIVE {_browsed(_LIMITS)}, {_STATS}, {_cells(_ALPHAS)} SELECT corpus_id AS session_words, alpha, vocab FROM cells"
ORACLES["daily_review_load"] = f"WITH RECURSIVE {_browsed(_LIMITS)}, {_STATS}, {_cells(_ALPHAS)} SELECT corpus_id AS session_words, alpha, round(vocab / days, 6) AS words_per_day FROM cells"
ORACLES["browse_short_sessions"] = f"WITH RECURSIVE {_browsed(_LIMITS)} SELECT corpus_id AS session_words, count(*) AS sessions, sum((n <= corpus_id)::INTEGER)::BIGINT AS short FROM sz SEMI JOIN rd USING (corpus_id, s) GROUP BY corpus_id"
ORACLES["browse_revisit_s_stem"] = f"""WITH RECURSIVE {_browsed("(100), (10000)").replace("words AS (SELECT corpus_id, lemma,", f"words AS (SELECT corpus_id, {_STEM} AS lemma,")}, {_STATS}, {_cells(_ALPHAS)}
SELECT corpus_id AS session_words, alpha, vocab, lemmas_with_gap, round(days, 6) AS revisit_days FROM cells"""
ORACLES["browse_revisit_n100_a90"] = f"""WITH RECURSIVE {_browsed('(100)')}, {_STATS}, {_cells((0.9,))}
SELECT (SELECT count(DISTINCT s) FROM rd) AS sessions, (SELECT count(*) FROM rd) AS page_views, (SELECT sum(n) FROM rd)::BIGINT AS words, vocab, round(days, 6) AS revisit_days, round(vocab / days, 6) AS words_per_day FROM cells"""

# ---------------------------------------------------------------- memory

_DAY = "epoch_us(ts) / 86400000000.0"
_GAMMA = "(2.0 * pow({h}, -0.2) * pow(2.0, -({r})) + 1.0)"


def _fold(success: str, lapse: str = "keep", first: str = "1.0") -> str:
    r = "pow(2.0, -greatest(x.d - f.last, 0.0) / f.h)"
    grown = f"f.h * {_GAMMA.format(h='f.h', r=r)}"
    missed = {"keep": "f.h", "reset": "1.0", "shrink": "f.h / 2"}[lapse]
    return f"""{_EVENTS}, x AS (SELECT user_id, k, event_id, ts, event_type, {_DAY} AS d, {success} AS ok, row_number() OVER (PARTITION BY user_id, k ORDER BY {_DAY}, event_id) AS n FROM ev),
f AS (SELECT user_id, k, n, event_id, ts, CASE WHEN ok THEN {first} ELSE {missed.replace('f.h', '1.0')} END::DOUBLE AS h, {'CASE WHEN ok THEN d END' if lapse == 'keep' else 'd'} AS last FROM x WHERE n = 1
  UNION ALL SELECT x.user_id, x.k, x.n, x.event_id, x.ts, CASE WHEN NOT x.ok THEN {missed} WHEN f.last IS NULL THEN {first} ELSE {grown} END, CASE WHEN x.ok THEN x.d ELSE {'f.last' if lapse == 'keep' else 'x.d'} END FROM f JOIN x ON x.user_id = f.user_id AND x.k = f.k AND x.n = f.n + 1),
z AS (SELECT user_id, k AS lemma_id, max(n) AS exposures, arg_max(h, n) AS half_life, arg_max(last, n) AS last_day FROM f GROUP BY ALL), now AS (SELECT max({_DAY}) AS now FROM events)"""


_STATE = "SELECT user_id, lemma_id, exposures::INTEGER AS exposures, round(half_life, 6) AS half_life, round(last_day, 6) AS last_day FROM z"
ORACLES["tutor_replay"] = f"WITH RECURSIVE {_fold('true')} {_STATE}"
ORACLES["tutor_feedback"] = f"WITH RECURSIVE {_fold(chr(39).join(['event_type <> ', 'error', '']), 'shrink')} {_STATE}"
for _lapse in ("keep", "reset"):
    ORACLES[f"tutor_feedback_{_lapse}"] = f"WITH RECURSIVE {_fold(chr(39).join(['event_type <> ', 'error', '']), _lapse)} {_STATE}"
ORACLES["tutor_first_boost"] = f"WITH RECURSIVE {_fold('true', first='3.0')} {_STATE}"
_QUIZ = f"event_type <> 'purchase' OR floor({_draw(chr(39) + '42' + chr(39), chr(39) + 'picked' + chr(39), 'event_id')} * 5) = floor({_draw(chr(39) + '42' + chr(39), chr(39) + 'quiz' + chr(39), 'event_id')} * 5)"
ORACLES["tutor_quiz"] = f"WITH RECURSIVE {_fold(_QUIZ, 'shrink')} {_STATE}"
ORACLES["stream_tutor"] = ORACLES["tutor_replay"]
_R_NOW = "pow(2.0, -greatest(now - last_day, 0.0) / half_life)"
ORACLES["tutor_recall_now"] = f"WITH RECURSIVE {_fold('true')} SELECT user_id, lemma_id, round({_R_NOW}, 6) AS r, round({_GAMMA.format(h='half_life', r=_R_NOW)}, 6) AS gamma, round(last_day - half_life * log2(0.9), 6) AS due_day FROM z, now"
ORACLES["tutor_due"] = f"WITH RECURSIVE {_fold('true')} SELECT user_id, lemma_id, round(now - (last_day - half_life * log2(0.9)), 6) AS overdue_days FROM z, now WHERE now - (last_day - half_life * log2(0.9)) > 0"
ORACLES["tutor_asof"] = f"""WITH RECURSIVE {_fold('true').replace('FROM ev)', "FROM ev WHERE event_type <> 'view')")}, v AS (SELECT event_id, user_id, k, ts FROM ev WHERE event_type = 'view')
SELECT v.event_id, v.user_id, v.k AS lemma_id, round(epoch_us(v.ts) / 86400000000.0 - f.last, 6) AS t_days, round(coalesce(pow(2.0, -greatest(epoch_us(v.ts) / 86400000000.0 - f.last, 0.0) / f.h), 0.0), 6) AS r
FROM v ASOF LEFT JOIN f ON v.user_id = f.user_id AND v.k = f.k AND v.ts > f.ts"""
ORACLES["tutor_slack"] = f"""WITH RECURSIVE {_fold('true')}, nx AS (SELECT f.user_id, f.k, x.d - (f.last - f.h * log2(0.9)) AS late FROM f JOIN x ON x.user_id = f.user_id AND x.k = f.k AND x.n = f.n + 1)
SELECT user_id, k AS lemma_id, count(*) AS delays, round(avg(late), 6) AS mean_delay FROM nx GROUP BY ALL"""
ORACLES["tutor_free_schedule"] = f"""WITH RECURSIVE {_EVENTS}, p AS (SELECT 0 AS revision, 0.0::DOUBLE AS day, 1.0::DOUBLE AS h UNION ALL SELECT revision + 1, day - h * log2(0.9), h * {_GAMMA.format(h='h', r='0.9')} FROM p WHERE revision < 8)
SELECT l::INTEGER AS lemma_id, revision, round(day, 6) AS day, round(h, 6) AS half_life FROM p, (SELECT DISTINCT k FROM ev WHERE k IS NOT NULL) t(l)"""
ORACLES["reading_sessions"] = """WITH p AS (SELECT user_id, ts, CASE WHEN date_diff('microsecond', lag(ts) OVER q, ts) < 43200000000 THEN 0 ELSE 1 END AS fresh FROM events WINDOW q AS (PARTITION BY user_id ORDER BY ts)),
n AS (SELECT user_id, ts, sum(fresh) OVER (PARTITION BY user_id ORDER BY ts RANGE BETWEEN UNBOUNDED PRECEDING AND CURRENT ROW) AS s FROM p)
SELECT user_id, min(ts) AS session_start, count(*) AS exposures, round(date_diff('microsecond', min(ts), max(ts)) / 3.6e9, 6) AS hours FROM n GROUP BY user_id, s"""
ORACLES["clicks_sliding"] = "SELECT time_bucket(INTERVAL 12 HOURS, ts) - w * INTERVAL 12 HOURS AS window_start, user_id, count(*) AS clicks FROM events CROSS JOIN (VALUES (0), (1)) v(w) WHERE event_type = 'click' GROUP BY ALL"
ORACLES["stream_clicks"] = "SELECT date_trunc('day', ts) AS window_start, user_id, count(*) AS clicks FROM events WHERE event_type = 'click' GROUP BY ALL"

# ---------------------------------------------------------------- context

_RUNS = f"""{_DOCS}, {_EACH}, runs AS (SELECT doc_id, i::INTEGER AS pos, lag(lemma, 2) OVER q AS a, lag(lemma) OVER q AS b, lemma AS w FROM each WHERE lang = 'en' WINDOW q AS (PARTITION BY doc_id ORDER BY i)),
uni AS (SELECT w, count(*) AS n FROM runs GROUP BY 1), tot AS (SELECT count(*) AS n FROM runs),
bi AS (SELECT b, w, count(*) AS n FROM runs WHERE b IS NOT NULL GROUP BY ALL), bc AS (SELECT b, sum(n) AS n, count(*) AS d FROM bi GROUP BY 1),
tri AS (SELECT a, b, w, count(*) AS n FROM runs WHERE a IS NOT NULL GROUP BY ALL), tc AS (SELECT a, b, sum(n) AS n FROM tri GROUP BY ALL)"""
_SHARES = """sh AS (SELECT runs.*, coalesce(uni.n / tot.n, 0) AS p1, coalesce(bi.n / bc.n, 0) AS p2, coalesce(tri.n / tc.n, 0) AS p3, bi.n AS n2, bc.n AS nb, bc.d AS db
  FROM runs CROSS JOIN tot JOIN uni ON uni.w = runs.w LEFT JOIN bi ON bi.b = runs.b AND bi.w = runs.w LEFT JOIN bc ON bc.b = runs.b LEFT JOIN tri ON tri.a = runs.a AND tri.b = runs.b AND tri.w = runs.w LEFT JOIN tc ON tc.a = runs.a AND tc.b = runs.b)"""
ORACLES["lm_bigram"] = f"WITH {_RUNS} SELECT bi.b AS ctx, bi.w, bi.n, round(bi.n / bc.n, 6) AS p FROM bi JOIN bc USING (b) WHERE bi.n >= 5"
ORACLES["lm_trigram_score"] = f"WITH {_RUNS}, {_SHARES} SELECT doc_id, pos, w AS lemma, round(0.5 * p3 + 0.3 * p2 + 0.2 * p1, 6) AS g FROM sh"
ORACLES["lm_backoff"] = f"WITH {_RUNS}, {_SHARES} SELECT doc_id, pos, w AS lemma, round(CASE WHEN p3 > 0 THEN p3 WHEN p2 > 0 THEN 0.4 * p2 ELSE 0.16 * p1 END, 6) AS g FROM sh"
ORACLES["lm_kneser_ney"] = f"""WITH {_RUNS}, {_SHARES}, co AS (SELECT w, count(*) AS c FROM bi GROUP BY 1), al AS (SELECT count(*) AS c FROM bi)
SELECT doc_id, pos, sh.w AS lemma, round(CASE WHEN nb IS NULL THEN coalesce(co.c / al.c, 0) ELSE greatest(coalesce(n2, 0) - 0.75::DOUBLE, 0) / nb + 0.75::DOUBLE * db / nb * coalesce(co.c / al.c, 0) END, 6) AS g FROM sh CROSS JOIN al LEFT JOIN co ON co.w = sh.w"""


def _kn3(train: str, scored: str) -> str:
    """Words of the scored runs after the two before them, by counts of the training runs."""
    return f"""t1 AS (SELECT w, count(*) AS c FROM (SELECT DISTINCT b, w FROM {train} WHERE b IS NOT NULL) GROUP BY 1), t0 AS (SELECT sum(c) AS c FROM t1),
t2 AS (SELECT b, w, count(DISTINCT a) AS c FROM {train} WHERE b IS NOT NULL GROUP BY ALL), t2s AS (SELECT b, sum(c) AS s, count(*) FILTER (c > 0) AS d FROM t2 GROUP BY 1),
t3 AS (SELECT a, b, w, count(*) AS c FROM {train} WHERE a IS NOT NULL GROUP BY ALL), t3s AS (SELECT a, b, sum(c) AS s, count(*) AS d FROM t3 GROUP BY ALL),
k1 AS (SELECT r.*, coalesce(t1.c / t0.c, 0) AS q1, t2.c AS c2, t2s.s AS s2, t2s.d AS d2, t3.c AS c3, t3s.s AS s3, t3s.d AS d3 FROM {scored} r CROSS JOIN t0 LEFT JOIN t1 ON t1.w = r.w LEFT JOIN t2 ON t2.b = r.b AND t2.w = r.w LEFT JOIN t2s ON t2s.b = r.b
  LEFT JOIN t3 ON t3.a = r.a AND t3.b = r.b AND t3.w = r.w LEFT JOIN t3s ON t3s.a = r.a AND t3s.b = r.b),
k2 AS (SELECT *, CASE WHEN coalesce(s2, 0) = 0 THEN q1 ELSE greatest(coalesce(c2, 0) - 0.75::DOUBLE, 0) / s2 + 0.75::DOUBLE * d2 / s2 * q1 END AS q2 FROM k1),
k3 AS (SELECT *, CASE WHEN coalesce(s3, 0) = 0 THEN q2 ELSE greatest(coalesce(c3, 0) - 0.75::DOUBLE, 0) / s3 + 0.75::DOUBLE * d3 / s3 * q2 END AS g FROM k2)"""


ORACLES["lm_kneser_ney_trigram"] = f"WITH {_RUNS}, {_kn3('runs', 'runs')} SELECT doc_id, pos, w AS lemma, round(g, 6) AS g FROM k3"
ORACLES["lm_held_out"] = " UNION ALL ".join(
    f"SELECT * FROM (WITH {_RUNS}, tr AS (SELECT * FROM runs WHERE doc_id % 2 <> {i}), sc AS (SELECT * FROM runs WHERE doc_id % 2 = {i}), {_kn3('tr', 'sc')} SELECT {i} AS fold, count(*) AS words, count(*) FILTER (g = 0) AS unknown, round(avg(CASE WHEN g > 0 THEN -log2(g) END), 6) AS bits FROM k3)" for i in (0, 1))
ORACLES["lm_frequency"] = f"WITH {_RUNS} SELECT uni.w AS lemma, uni.n AS f_corpus, round(uni.n / tot.n, 6) AS g FROM uni, tot"
ORACLES["frequency_in_text"] = f"WITH {_RUNS} SELECT doc_id, pos, runs.w AS lemma, round((uni.n / tot.n + count(*) OVER (PARTITION BY doc_id, runs.w) / count(*) OVER (PARTITION BY doc_id)) / 2, 6) AS g FROM runs JOIN uni ON uni.w = runs.w, tot"
_STOP = "('a','an','and','are','as','at','be','but','by','for','from','had','has','have','he','her','his','i','in','is','it','its','no','not','of','on','or','she','so','that','the','their','them','they','this','to','was','we','were','what','when','which','who','will','with','you')"
_FOLD = "replace(replace(replace(replace(replace(replace(replace(replace(translate({}, 'àáâäãèéêëìíîïòóôöõùúûüçñß', 'aaaaaeeeeiiiiooooouuuucns'), 'ph', 'f'), 'th', 't'), 'ck', 'k'), 'qu', 'k'), 'c', 'k'), 'y', 'i'), 'w', 'v'), 'z', 's')"
_VOCAB = f"{_DOCS}, {_EACH}, vc AS (SELECT lang, lemma, count(*) AS n FROM each GROUP BY ALL), vocab AS (SELECT lang, lemma, n, row_number() OVER (PARTITION BY lang ORDER BY n DESC, lemma) AS rank FROM vc)"
_POOL = rf"""se AS (SELECT unnest(regexp_extract_all(text, '[^.!?]+[.!?]*')) AS s FROM docs WHERE lang = 'en'), sw AS (SELECT unnest(regexp_extract_all(s, '\p{{L}}+')[2:]) AS w FROM se),
proper AS (SELECT lower(w) AS lemma FROM sw GROUP BY 1 HAVING count(*) FILTER (regexp_matches(w, '^\p{{Lu}}')) > 0.5 * count(*)),
own AS (SELECT lemma, n, {_FOLD.format('lemma')} AS f FROM vocab WHERE lang = 'en' AND rank <= 500 AND length(lemma) >= 3 AND lemma NOT IN {_STOP} AND lemma NOT IN (SELECT lemma FROM proper)),
oth AS (SELECT DISTINCT {_FOLD.format('lemma')} AS g FROM vocab WHERE lang <> 'en' AND rank <= 500),
cog AS (SELECT DISTINCT lemma FROM own JOIN oth ON levenshtein(f, g) < (1 - 0.6::DOUBLE) * greatest(length(f), length(g))),
pool AS (SELECT lemma, n, row_number() OVER (ORDER BY md5('42|' || lemma), lemma) AS rank FROM own WHERE lemma NOT IN (SELECT lemma FROM cog) QUALIFY rank <= 78)"""
ORACLES["word_pool"] = f"WITH {_VOCAB}, {_POOL} SELECT lemma, n, rank::INTEGER AS rank FROM pool"
ORACLES["word_groups"] = f"WITH {_VOCAB}, {_POOL} SELECT lemma, ((rank - 1) % 3)::INTEGER AS wgroup, CASE WHEN ((rank - 1) // 3) % 2 = 0 THEN 'easy' ELSE 'random' END AS arm FROM pool"
_MIXED = f"{_RUNS}, {_SHARES}, vc AS (SELECT lang, lemma, count(*) AS n FROM each GROUP BY ALL), vocab AS (SELECT lang, lemma, n, row_number() OVER (PARTITION BY lang ORDER BY n DESC, lemma) AS rank FROM vc)"
_PICK = "SELECT lemma, doc_id, pos, round(g, 6) AS g, rank::INTEGER AS rank FROM (SELECT w AS lemma, doc_id, pos, round(0.0 * p3 + 0.7 * p2 + 0.3 * p1, 9) AS g, row_number() OVER (PARTITION BY w ORDER BY {} doc_id, pos) AS rank FROM sh WHERE w IN (SELECT lemma FROM pool)) WHERE rank <= 7"
ORACLES["easy_contexts"] = f"WITH {_MIXED}, {_POOL} {_PICK.format('round(0.0 * p3 + 0.7 * p2 + 0.3 * p1, 9) DESC,')}"
ORACLES["random_contexts"] = f"WITH {_MIXED}, {_POOL} " + _PICK.format("md5(concat_ws('|', '42', w, doc_id, pos)),")

_ARM = "SELECT wgroup, '{0}' AS arm, lemma, doc_id, pos, round(g, 6) AS g, rank::INTEGER AS rank FROM (SELECT wgroup, lemma, doc_id, pos, round(0.0 * p3 + 0.7 * p2 + 0.3 * p1, 9) AS g, row_number() OVER (PARTITION BY w ORDER BY {1}, doc_id, pos) AS rank FROM sh JOIN gps ON lemma = w WHERE arm = '{0}') WHERE rank <= 7"
ORACLES["embedded_instances"] = f"""WITH {_MIXED}, {_POOL}, gps AS (SELECT lemma, ((rank - 1) % 3)::INTEGER AS wgroup, CASE WHEN ((rank - 1) // 3) % 2 = 0 THEN 'easy' ELSE 'random' END AS arm FROM pool)
{_ARM.format('easy', 'round(0.0 * p3 + 0.7 * p2 + 0.3 * p1, 9) DESC')} UNION ALL {_ARM.format('random', "md5(concat_ws('|', '42', w, doc_id, pos))")}"""

# ---------------------------------------------------------------- selection

_CAND = f"""{_MIXED}, {_fold('true')}, nu AS (SELECT count(DISTINCT user_id) AS users FROM events),
cand AS (SELECT doc_id, pos, sh.w AS lemma, coalesce({_R_NOW}, 0) AS r, 0.0 * p3 + 0.7 * p2 + 0.3 * p1 AS g, coalesce(half_life, 1.0) AS h
  FROM sh CROSS JOIN nu CROSS JOIN now LEFT JOIN vocab ON vocab.lang = 'en' AND vocab.rank <= 100 AND vocab.lemma = sh.w LEFT JOIN z ON z.user_id = sh.doc_id % nu.users AND z.lemma_id = vocab.rank - 1 WHERE length(sh.w) >= 3 AND sh.w NOT IN {_STOP}),
kk AS (SELECT doc_id, floor(len(ws) * 0.05::DOUBLE)::INTEGER AS k FROM docs WHERE lang = 'en')"""


def _select(r: str = "r", g: str = "g", h: str = "h", order: str | None = None, per_lemma: bool = False) -> str:
    gamma = _GAMMA.format(h="h", r="r")
    best = "QUALIFY row_number() OVER (PARTITION BY doc_id, lemma ORDER BY priority DESC, pos) = 1" if per_lemma else ""
    return f"""{_CAND}, sc AS (SELECT doc_id, pos, lemma, {r} AS r, {g} AS g, {h} AS h FROM cand),
pr AS (SELECT doc_id, pos, lemma, r, g, r + g - r * g AS p, {gamma} AS gamma, round({order or f'(r + g - r * g) * {gamma}'}, 9) AS priority FROM sc),
pl AS (SELECT * FROM pr {best}),
rk AS (SELECT *, row_number() OVER (PARTITION BY doc_id ORDER BY priority DESC, pos) AS rank FROM pl),
sel AS (SELECT rk.* FROM rk JOIN kk USING (doc_id) WHERE rank <= k)"""


_AHEAD_ROWS = """ww AS (SELECT doc_id, i, lemma, row_number() OVER (ORDER BY doc_id, i) - 1 AS place FROM each WHERE lang = 'en'),
la AS (SELECT doc_id, i AS pos, count(*) OVER (PARTITION BY lemma ORDER BY place RANGE BETWEEN 1 FOLLOWING AND 2000 FOLLOWING) AS upcoming FROM ww)"""


def _with_upcoming(select: str) -> str:
    """The selection over candidates that know how often their word comes up again."""
    return f"{select}".replace("sc AS (SELECT doc_id, pos, lemma,", f"{_AHEAD_ROWS}, sc AS (SELECT doc_id, pos, lemma, upcoming,").replace("AS h FROM cand)", "AS h FROM cand JOIN la USING (doc_id, pos))").replace("pr AS (SELECT doc_id, pos, lemma, r, g,", "pr AS (SELECT doc_id, pos, lemma, upcoming, r, g,")


_SEL = "SELECT doc_id, pos, lemma, round(r, 6) AS r, round(g, 6) AS g, round(p, 6) AS p, round(gamma, 6) AS gamma, round(priority, 6) AS priority, rank::INTEGER AS rank FROM sel"
ORACLES["select_topk"] = f"WITH RECURSIVE {_select()} {_SEL}"
ORACLES["select_topk_lemma"] = f"WITH RECURSIVE {_select(per_lemma=True)} {_SEL}"
ORACLES["select_tutor_only"] = f"WITH RECURSIVE {_select(g='0.0::DOUBLE')} {_SEL}"
ORACLES["select_context_only"] = f"WITH RECURSIVE {_select(r='0.0::DOUBLE', h='1.0::DOUBLE')} {_SEL}"
ORACLES["select_random"] = f"WITH RECURSIVE {_select(order=_draw(chr(39) + '42' + chr(39), 'doc_id', 'pos'))} {_SEL}"
ORACLES["select_topk_all"] = f"WITH RECURSIVE {_select(per_lemma=True)} SELECT pr.doc_id, pr.pos, lemma, round(pr.r, 6) AS r, round(pr.g, 6) AS g, round(pr.p, 6) AS p, round(pr.gamma, 6) AS gamma, round(pr.priority, 6) AS priority, rank::INTEGER AS rank FROM pr JOIN (SELECT doc_id, lemma, rank FROM sel) USING (doc_id, lemma)"
ORACLES["select_lookahead"] = f"WITH RECURSIVE {_with_upcoming(_select(order='(r + g - r * g) * ' + _GAMMA.format(h='h', r='r') + ' * (1 + 0.25::DOUBLE * log2(1 + upcoming))'))} {_SEL}"
# greedy, one choice a turn: a lemma that has been shown has recall one after its first place shown, and a longer half-life
_SHOWN = "list_min(list_transform(list_filter(taken, lambda t: t.l = c.lemma), lambda t: t.p))"
_H2 = f"CASE WHEN {_SHOWN} IS NULL THEN c.h ELSE c.h * {_GAMMA.format(h='c.h', r='c.r')} END"
_R2 = f"CASE WHEN {_SHOWN} < c.pos THEN 1.0::DOUBLE ELSE c.r END"
ORACLES["select_rescored"] = f"""WITH RECURSIVE {_CAND}, k2 AS (SELECT doc_id, floor(len(ws) * 0.02::DOUBLE)::INTEGER AS k FROM docs WHERE lang = 'en'),
cd AS MATERIALIZED (SELECT doc_id, pos, lemma, r, g, h FROM cand),
gr AS (SELECT doc_id, k, 0 AS rank, []::STRUCT(l VARCHAR, p INTEGER)[] AS taken, NULL::INTEGER AS pos, NULL::VARCHAR AS lemma, NULL::DOUBLE AS priority FROM k2
  UNION ALL SELECT doc_id, k, rank + 1, list_append(taken, {{'l': best.l, 'p': -best.p}}), -best.p, best.l, best.v FROM (
    SELECT doc_id, k, rank, taken, max({{'v': round((r2 + g - r2 * g) * {_GAMMA.format(h='h2', r='r2')}, 9), 'p': -pos, 'l': lemma}}) AS best
    FROM (SELECT q.doc_id, q.k, q.rank, q.taken, c.pos, c.lemma, c.g, {_R2} AS r2, {_H2} AS h2 FROM gr q JOIN cd c ON c.doc_id = q.doc_id WHERE q.rank < q.k AND NOT list_contains(list_transform(q.taken, lambda t: t.p), c.pos)) GROUP BY doc_id, k, rank, taken))
SELECT doc_id, pos, lemma, round(priority, 6) AS priority, rank::INTEGER AS rank FROM gr WHERE rank > 0"""
ORACLES["lookahead_weights"] = f"WITH {_EN} SELECT doc_id, pos, lemma, count(*) OVER (PARTITION BY lemma ORDER BY pos RANGE BETWEEN 1 FOLLOWING AND 2000 FOLLOWING) AS upcoming FROM words"
_PAIRS = f"{_RUNS}, sums AS (SELECT sum(n) AS t FROM bi), prs AS (SELECT b AS w1, w AS w2, n, sum(n) OVER (PARTITION BY b) AS n1, sum(n) OVER (PARTITION BY w) AS n2, t FROM bi, sums)"
ORACLES["collocations"] = f"WITH {_PAIRS} SELECT w1, w2, n, round(ln(n::DOUBLE * t / (n1::DOUBLE * n2)) / -ln(n::DOUBLE / t), 6) AS npmi FROM prs WHERE n >= 20"
_PART = "CASE WHEN {k} > 0 THEN {k} * ln({k} / ({e})) ELSE 0 END"
ORACLES["collocations_llr"] = f"""WITH {_PAIRS}, dbl AS (SELECT w1, w2, n AS cnt, n::DOUBLE AS n, n1::DOUBLE AS n1, n2::DOUBLE AS n2, t::DOUBLE AS t FROM prs WHERE n >= 20)
SELECT w1, w2, cnt AS n, round(2 * ({_PART.format(k='n', e='n1 * n2 / t')} + {_PART.format(k='(n1 - n)', e='n1 * (t - n2) / t')} + {_PART.format(k='(n2 - n)', e='(t - n1) * n2 / t')} + {_PART.format(k='(t - n1 - n2 + n)', e='(t - n1) * (t - n2) / t')}), 6) AS llr FROM dbl"""
ORACLES["collocations_3"] = f"""WITH {_RUNS}, ts AS (SELECT a AS w1, b AS w2, w AS w3, n, sum(n) OVER (PARTITION BY a) AS n1, sum(n) OVER (PARTITION BY b) AS n2, sum(n) OVER (PARTITION BY w) AS n3, sum(n) OVER () AS t FROM tri)
SELECT w1, w2, w3, n, round(ln(n::DOUBLE * t * t / (n1::DOUBLE * n2 * n3)) / (-2 * ln(n::DOUBLE / t)), 6) AS npmi FROM ts WHERE n >= 5"""
ORACLES["density_ramp"] = "SELECT user_id, d::INTEGER AS day, round(0.05 + 0.95 * least(1.0, d / 30.0), 6) AS density, CASE WHEN 0.05::DOUBLE + 0.95::DOUBLE * least(1.0, d / 30.0) < 0.6 THEN 'base_to_target' ELSE 'target_to_base' END AS direction FROM (SELECT DISTINCT user_id, date_diff('day', min(ts::DATE) OVER (PARTITION BY user_id), ts::DATE) AS d FROM events)"

# ---------------------------------------------------------------- translation

_LEX = """en AS (SELECT lemma, rank FROM vocab WHERE lang = 'en'), de AS (SELECT lemma AS target, rank FROM vocab WHERE lang = 'de'),
lex AS (SELECT en.lemma, en.rank, s AS sense, target, (SELECT coalesce(list_sort(list(c.lemma)), []) FROM en c WHERE c.rank BETWEEN en.rank + 1 + 5 * (s - 1) AND en.rank + 5 * s) AS cues FROM en CROSS JOIN (VALUES (1), (2)) v(s) JOIN de ON de.rank = en.rank + s - 1)"""
ORACLES["lexicon_de"] = f"WITH {_VOCAB}, {_LEX} SELECT lemma, 'de' AS target_lang, sense, target, array_to_string(cues, ' ') AS cues FROM lex"
_SENT = r"""sp AS (SELECT doc_id, unnest(ps) AS s, unnest(range(len(ps)))::INTEGER AS sent FROM (SELECT doc_id, regexp_extract_all(text, '[^.!?]+[.!?]*') AS ps FROM docs WHERE lang = 'en')),
sn AS (SELECT doc_id, sent, regexp_extract_all(lower(s), '\p{L}+') AS sws FROM sp),
sf AS (SELECT *, coalesce(sum(len(sws)) OVER (PARTITION BY doc_id ORDER BY sent ROWS BETWEEN UNBOUNDED PRECEDING AND 1 PRECEDING), 0) AS first FROM sn),
spos AS (SELECT doc_id, sent, sws, unnest(range(first::BIGINT, first::BIGINT + len(sws)))::INTEGER AS pos FROM sf)"""
_T1 = f"WITH RECURSIVE {_select()}, {_LEX}, {_SENT}, got AS (SELECT sel.doc_id, sel.pos, sel.lemma, spos.sent, spos.sws, lex.target FROM sel JOIN spos USING (doc_id, pos) JOIN lex ON lex.lemma = sel.lemma AND lex.sense = 1)"
ORACLES["translate_in_context"] = f"{_T1} SELECT doc_id, pos, lemma, sent, target FROM got"
ORACLES["translate_senses"] = f"""WITH RECURSIVE {_select()}, {_LEX}, {_SENT}
SELECT sel.doc_id, sel.pos, sel.lemma, spos.sent, lex.target FROM sel JOIN spos USING (doc_id, pos) JOIN lex ON lex.lemma = sel.lemma
QUALIFY row_number() OVER (PARTITION BY sel.doc_id, sel.pos ORDER BY len(list_intersect(lex.cues, spos.sws)) DESC, lex.sense) = 1"""
ORACLES["translate_cost"] = f"{_T1}, ks AS (SELECT array_to_string(spos.sws, ' ') AS key, count(*) AS n FROM sel JOIN spos USING (doc_id, pos) GROUP BY 1) SELECT sum(n)::BIGINT AS selected, count(*) AS distinct_sentences, sum(length(key))::BIGINT AS characters FROM ks"
_SEGS = r"""sg AS (SELECT doc_id, unnest(ps) AS seg, unnest(range(len(ps))) AS j FROM (SELECT doc_id, regexp_extract_all(text, '\p{L}+|[^\p{L}]+') AS ps FROM docs WHERE lang = 'en')),
sw2 AS (SELECT *, regexp_matches(seg, '^\p{L}') AS word, sum(CASE WHEN regexp_matches(seg, '^\p{L}') THEN 1 ELSE 0 END) OVER (PARTITION BY doc_id ORDER BY j) - 1 AS pos FROM sg)"""
_ESC = "replace(replace(replace({}, '&', '&amp;'), '<', '&lt;'), '>', '&gt;')"
_NEW = "SELECT sw2.doc_id, string_agg(CASE WHEN word AND got.target IS NOT NULL THEN {} ELSE {} END, '' ORDER BY j) AS text FROM sw2 LEFT JOIN got ON got.doc_id = sw2.doc_id AND got.pos = sw2.pos GROUP BY 1"
_MARK = f"""'<mark data-original="' || {_ESC.format('seg')} || '">' || {_ESC.format('got.target')} || '</mark>'"""
ORACLES["render_marked"] = f"{_T1}, {_SEGS}, nt AS ({_NEW.format(_MARK, _ESC.format('seg'))}) SELECT docs.doc_id, coalesce(nt.text, {_ESC.format('docs.text')}) AS text FROM docs LEFT JOIN nt USING (doc_id) WHERE lang = 'en'"
ORACLES["augment_documents"] = f"{_T1}, {_SEGS}, nt AS ({_NEW.format('got.target', 'seg')}), ng AS (SELECT doc_id, count(*) AS n FROM got GROUP BY 1) SELECT docs.doc_id, len(ws)::INTEGER AS n_words, coalesce(ng.n, 0) AS n_replaced, coalesce(nt.text, docs.text) AS text FROM docs LEFT JOIN nt USING (doc_id) LEFT JOIN ng USING (doc_id) WHERE lang = 'en'"
_ALTERED = "ng AS (SELECT doc_id, count(*) AS n FROM got GROUP BY 1) SELECT docs.doc_id, len(ws)::INTEGER AS n_words, coalesce(ng.n, 0) AS n_replaced, coalesce(nt.text, docs.text) AS text FROM docs LEFT JOIN nt USING (doc_id) LEFT JOIN ng USING (doc_id) WHERE lang = 'en'"
ORACLES["augment_promoted"] = f"""WITH RECURSIVE {_select().replace('pl AS (SELECT * FROM pr ', 'pl AS (SELECT * FROM pr WHERE lemma IN (SELECT en.lemma FROM vocab en JOIN vocab de ON de.rank = en.rank WHERE en.lang = ' + chr(39) + 'en' + chr(39) + ' AND de.lang = ' + chr(39) + 'de' + chr(39) + ' AND en.rank <= 400) ')}, {_LEX}, {_SENT},
got AS (SELECT sel.doc_id, sel.pos, lex.target FROM sel JOIN spos USING (doc_id, pos) JOIN lex ON lex.lemma = sel.lemma AND lex.sense = 1), {_SEGS}, nt AS ({_NEW.format('got.target', 'seg')}), {_ALTERED}"""
ORACLES["converted_documents"] = f"WITH {_VOCAB}, {_LEX}, got AS (SELECT doc_id, i AS pos, target FROM each JOIN lex ON lex.lemma = each.lemma AND sense = 1 WHERE lang = 'en'), {_SEGS}, nt AS ({_NEW.format('got.target', 'seg')}), {_ALTERED}"


def _rounds(n: int) -> str:
    """Expectation maximisation, each round by a join of its own."""
    out = ["t0 AS (SELECT DISTINCT e, f, 1.0::DOUBLE AS t FROM cells)"]
    for i in range(n):
        out.append(f"c{i} AS (SELECT e, f, sum(m * n * t / z) AS c FROM (SELECT cells.*, t, sum(n * t) OVER (PARTITION BY pair_id, cells.f) AS z FROM cells JOIN t{i} t ON t.f = cells.f AND t.e IS NOT DISTINCT FROM cells.e) GROUP BY ALL)")
        out.append(f"t{i + 1} AS (SELECT e, f, c / sum(c) OVER (PARTITION BY e) AS t FROM c{i})")
    return ", ".join(out)


ORACLES["word_alignment"] = f"""WITH tw AS (SELECT conv_id, turn, role, regexp_extract_all(lower(coalesce(text, '')), '\\p{{L}}+') AS ws FROM conversations),
ps AS (SELECT a.conv_id * 1000 + a.turn AS pair_id, a.ws AS src, b.ws AS tgt FROM tw a JOIN tw b ON b.conv_id = a.conv_id AND b.turn = a.turn + 1 WHERE a.role = 'user' AND b.role = 'assistant'),
es AS (SELECT pair_id, e, count(*)::DOUBLE AS n FROM (SELECT pair_id, unnest(list_prepend(NULL, src)) AS e FROM ps) GROUP BY ALL), fs AS (SELECT pair_id, f, count(*)::DOUBLE AS m FROM (SELECT pair_id, unnest(tgt) AS f FROM ps) GROUP BY ALL),
cells AS (SELECT pair_id, e, n, f, m FROM es JOIN fs USING (pair_id)), {_rounds(5)} SELECT e, f, round(t, 6) AS t FROM t5 WHERE e IS NOT NULL"""
ORACLES["translate_reverse"] = f"""WITH {_VOCAB}, {_LEX}, {_SENT.replace("lang = 'en'", "lang = 'de'")}
SELECT each.doc_id, i::INTEGER AS pos, each.lemma, sent, lex.lemma AS target FROM each JOIN spos ON spos.doc_id = each.doc_id AND spos.pos = each.i JOIN lex ON lex.target = each.lemma AND lex.sense = 1 WHERE lang = 'de'"""

# ---------------------------------------------------------------- design

_CONDITIONS = ("embedded", "pre_table", "post_table")
_ASSIGN = ", ".join(f"({g}, {w}, '{c}')" for g, order in enumerate(permutations(_CONDITIONS)) for w, c in enumerate(order))
_CELLS = f"""pt AS (SELECT p::INTEGER AS participant, ((row_number() OVER (ORDER BY md5('42|participant|' || p), p) - 1) % 6)::INTEGER AS pgroup, row_number() OVER (ORDER BY md5('42|back|' || p), p) AS turn FROM range(58) t(p)),
wd AS (SELECT w::INTEGER AS word, (w % 3)::INTEGER AS wgroup, CASE WHEN (w // 3) % 2 = 0 THEN 'easy' ELSE 'random' END AS arm FROM range(78) t(w)),
cl AS (SELECT participant, pt.pgroup, turn, word, wd.wgroup, arm, condition FROM pt CROSS JOIN wd JOIN (VALUES {_ASSIGN}) a(pgroup, wgroup, condition) ON a.pgroup = pt.pgroup AND a.wgroup = wd.wgroup),
fg AS (SELECT participant, word FROM (SELECT participant, word, row_number() OVER (PARTITION BY participant, condition ORDER BY md5(concat_ws('|', '42', 'gap', participant, word)), word) AS r, count(*) OVER (PARTITION BY participant, condition) AS n FROM cl) WHERE r <= n // 3)"""
#: The same with participants and words from the given tables.
_KEYED = _CELLS.replace("FROM range(58) t(p)", "FROM (SELECT DISTINCT c_custkey % 58 FROM customer WHERE c_custkey IS NOT NULL) t(p)").replace("FROM range(78) t(w)", "FROM (SELECT DISTINCT p_partkey % 78 FROM part WHERE p_partkey IS NOT NULL) t(w)")
ORACLES["participant_groups"] = f"WITH {_KEYED} SELECT participant, pgroup FROM pt"
ORACLES["design_balance"] = f"WITH {_KEYED} SELECT condition, wgroup, pgroup, count(*) AS cells FROM cl GROUP BY CUBE (condition, wgroup, pgroup)"
ORACLES["ftg_items"] = f"WITH {_KEYED} SELECT participant, word FROM fg"
ORACLES["snippet_pool"] = f"WITH {_DOCS} SELECT doc_id, len(ws)::INTEGER AS n_words FROM docs WHERE lang = 'en' AND len(ws) BETWEEN 100 AND 2500"
# greedy, one snippet a turn: the need of each of a group's words shrinks by what the snippet brings
_COVER = f"""gw AS (SELECT ((rank - 1) % 3)::INTEGER AS wgroup, lemma, row_number() OVER (PARTITION BY (rank - 1) % 3 ORDER BY lemma) AS j FROM pool),
sn0 AS (SELECT doc_id, ws FROM docs WHERE lang = 'en' AND len(ws) BETWEEN 100 AND 2500),
cnt AS (SELECT wgroup, doc_id, j, count(*) AS n FROM (SELECT doc_id, unnest(ws) AS lemma FROM sn0) JOIN gw USING (lemma) GROUP BY ALL),
vec AS MATERIALIZED (SELECT d.wgroup, d.doc_id, list(coalesce(n, 0) ORDER BY g.j) AS c FROM (SELECT DISTINCT wgroup, doc_id FROM cnt) d JOIN gw g ON g.wgroup = d.wgroup LEFT JOIN cnt ON cnt.wgroup = d.wgroup AND cnt.doc_id = d.doc_id AND cnt.j = g.j GROUP BY ALL),
cov AS (SELECT wgroup, 0 AS round, NULL::BIGINT AS doc_id, 0::BIGINT AS gain, list_transform(range(count(*)), lambda x: 7::BIGINT) AS need, []::BIGINT[] AS taken FROM gw GROUP BY wgroup
  UNION ALL SELECT wgroup, round + 1, -best.d, best.g, list_transform(list_zip(need, best.c), lambda x: greatest(x[1] - x[2], 0)), list_append(taken, -best.d) FROM (
    SELECT wgroup, round, need, taken, max({{'g': gain2, 'd': -doc, 'c': c}}) AS best FROM (SELECT q.wgroup, q.round, q.need, q.taken, v.doc_id AS doc, v.c, list_sum(list_transform(list_zip(q.need, v.c), lambda x: least(x[1], x[2])))::BIGINT AS gain2
      FROM cov q JOIN vec v ON v.wgroup = q.wgroup WHERE q.round < 47 AND list_sum(q.need) > 0 AND NOT list_contains(q.taken, v.doc_id)) WHERE gain2 > 0 GROUP BY ALL))"""
ORACLES["snippet_cover"] = f"WITH RECURSIVE {_VOCAB}, {_POOL}, {_COVER} SELECT wgroup, round::INTEGER AS round, doc_id, gain FROM cov WHERE round > 0"
ORACLES["study_pages"] = f"""WITH RECURSIVE {_VOCAB}, {_POOL}, {_COVER}, ch AS (SELECT wgroup, doc_id FROM cov WHERE round > 0),
pgs AS (SELECT wgroup, ((row_number() OVER (PARTITION BY wgroup ORDER BY md5('42|' || doc_id), doc_id) - 1) // 10 + 1)::INTEGER AS page, doc_id FROM ch),
un AS (SELECT doc_id FROM sn0 WHERE doc_id NOT IN (SELECT doc_id FROM ch) ORDER BY md5('43|' || doc_id), doc_id LIMIT 5)
SELECT wgroup, page, doc_id, true AS treated FROM pgs UNION ALL SELECT wgroup, last, doc_id, false FROM (SELECT wgroup, max(page) + 1 AS last FROM pgs GROUP BY 1) CROSS JOIN un"""
ORACLES["study_sections"] = f"WITH {_KEYED} SELECT DISTINCT participant, CASE condition WHEN 'pre_table' THEN 1 WHEN 'embedded' THEN 2 ELSE 3 END AS section, condition, wgroup FROM cl"
ORACLES["control_page"] = f"WITH {_DOCS} SELECT doc_id, len(ws)::INTEGER AS n_words FROM docs WHERE lang = 'en' AND len(ws) BETWEEN 100 AND 2500 ORDER BY md5('43|' || doc_id), doc_id LIMIT 5"
_MC = f"""{_CELLS}, op AS (SELECT participant, a.word, b.word AS option FROM pt CROSS JOIN wd a CROSS JOIN wd b
  QUALIFY row_number() OVER (PARTITION BY participant, a.word ORDER BY (a.word <> b.word)::INTEGER, md5(concat_ws('|', '42', participant, a.word, b.word)), b.word) <= 5),
mc AS (SELECT participant, word, (row_number() OVER (PARTITION BY participant, word ORDER BY md5(concat_ws('|', '42', 'slot', participant, word, option)), option))::INTEGER AS slot, option::VARCHAR AS option, word = option AS is_answer FROM op
  UNION ALL SELECT participant, word, 0, 'don''t know', false FROM pt CROSS JOIN wd)"""
_MC_KEYED = _MC.replace(_CELLS, _KEYED)
ORACLES["mc_items"] = f"WITH {_MC_KEYED} SELECT * FROM mc"
ORACLES["mc_retest"] = f"WITH {_MC_KEYED} SELECT participant, word, (row_number() OVER (PARTITION BY participant, word ORDER BY (slot <> 0)::INTEGER, md5(concat_ws('|', '44', participant, word, option)), option) - 1)::INTEGER AS slot, option, is_answer FROM mc"
ORACLES["mc_items_reverse"] = f"""WITH {_VOCAB}, {_POOL}, {_LEX}, {_MC}, nm AS (SELECT (pool.rank - 1)::INTEGER AS word, pool.lemma, target FROM pool JOIN lex ON lex.lemma = pool.lemma AND sense = 1)
SELECT participant, mc.word, nm.lemma AS prompt, slot, coalesce(o.target, option) AS option, is_answer FROM mc JOIN nm USING (word) LEFT JOIN nm o ON o.word::VARCHAR = option"""
ORACLES["ftg_graded"] = f"""WITH {_VOCAB}, {_POOL}, ky AS (SELECT (rank - 1)::INTEGER AS item, lemma AS key FROM pool), sy AS (SELECT key, v.lemma AS synonym FROM ky JOIN vocab v ON v.lang = 'en' AND v.rank = item * 2 + 502),
gv AS (SELECT k.item, k.key, s.synonym, CASE k.item % 7 WHEN 0 THEN upper(k.key[1]) || k.key[2:] WHEN 1 THEN k.key || 's' WHEN 2 THEN k.key[1:2] || k.key[2:] WHEN 3 THEN s.synonym WHEN 4 THEN n.key WHEN 5 THEN '  ' END AS answer
  FROM ky k LEFT JOIN ky n ON n.item = k.item + 1 LEFT JOIN sy s ON s.key = k.key),
ok AS (SELECT *, lower(trim(answer)) AS said FROM gv)
SELECT item, answer, CASE WHEN coalesce(said, '') = '' THEN 'unknown' WHEN levenshtein(said, key) <= 1 OR coalesce(levenshtein(said, synonym) <= 1, false) OR {_STEM.replace('lemma', 'said')} = {_STEM.replace('lemma', 'key')} OR coalesce({_STEM.replace('lemma', 'said')} = {_STEM.replace('lemma', 'synonym')}, false) THEN 'correct' ELSE 'incorrect' END AS outcome FROM ok"""
ORACLES["chance_baseline"] = f"WITH {_MC_KEYED} SELECT count(*) AS items, 0.2::DOUBLE AS expected, round(avg(is_answer::INTEGER), 6) AS simulated FROM mc WHERE slot = 1 + floor({_draw(chr(39) + '42' + chr(39), chr(39) + 'guess' + chr(39), 'participant', 'word')} * 5)"
ORACLES["participant_profile"] = """WITH p AS (SELECT c_acctbal AS balance, n_name AS nation, c_mktsegment AS segment FROM customer JOIN nation ON c_nationkey = n_nationkey)
SELECT 'balance' AS attribute, 'all' AS value, count(balance) AS n, 1.0::DOUBLE AS share, round(avg(balance), 6) AS mean, round(stddev_samp(balance), 6) AS sd FROM p
UNION ALL SELECT 'nation', nation, count(*), round(count(*) / (SELECT count(*) FROM p), 6), NULL, NULL FROM p GROUP BY nation
UNION ALL SELECT 'segment', segment, count(*), round(count(*) / (SELECT count(*) FROM p), 6), NULL, NULL FROM p GROUP BY segment"""

# ---------------------------------------------------------------- measures

_ANS = f"""{_CELLS}, ln AS (SELECT (o_custkey % 58)::INTEGER AS participant, (l_partkey % 78)::INTEGER AS word, CASE WHEN l_linestatus = 'F' THEN 'short' ELSE 'long' END AS phase, l_returnflag AS flag FROM lineitem JOIN orders ON l_orderkey = o_orderkey
  QUALIFY row_number() OVER (PARTITION BY o_custkey % 58, l_partkey % 78, l_linestatus ORDER BY l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate, l_returnflag) = 1),
an AS (SELECT cl.participant, cl.word, condition, arm, c AS component, phase, CASE flag WHEN 'R' THEN 'correct' WHEN 'A' THEN 'incorrect' ELSE 'unknown' END AS outcome
  FROM ln JOIN cl USING (participant, word) CROSS JOIN (VALUES ('mc', 32), ('ftg', 29)) v(c, back) WHERE (c = 'mc' OR (participant, word) IN (SELECT (participant, word) FROM fg)) AND (phase = 'short' OR turn <= back)),
ck AS (SELECT cl.participant, cl.word, arm, coalesce(n, 0) AS clicks FROM cl LEFT JOIN (SELECT (user_id % 58)::INTEGER AS participant, json_extract(props, '$.k')::INTEGER % 78 AS word, count(*) AS n FROM events WHERE event_type = 'click' GROUP BY ALL) USING (participant, word) WHERE condition = 'embedded')"""


def _ci(value: str, units: str) -> str:
    half = f"1.959964 * coalesce(stddev_samp({value}), 0) / sqrt(count({value}))"
    return f"count({value}) AS {units}, round(avg({value}), 6) AS mean, round(avg({value}) - {half}, 6) AS lo, round(avg({value}) + {half}, 6) AS hi"


def _p(t: str, df: str) -> str:
    """Two-sided p of Student's t: the finite sums, with their products as quotients of gamma functions."""
    c2 = f"pow(cos(atan(abs({t}) / sqrt({df}))), 2)"
    odd = f"2 / pi() * (atan(abs({t}) / sqrt({df})) + CASE WHEN {df} > 1 THEN sin(atan(abs({t}) / sqrt({df}))) * cos(atan(abs({t}) / sqrt({df}))) * list_sum(list_transform(range((({df} - 1) // 2)::BIGINT), lambda k: exp(lgamma(k + 1) - lgamma(k + 1.5)) * sqrt(pi()) / 2 * pow({c2}, k))) ELSE 0 END)"
    even = f"sin(atan(abs({t}) / sqrt({df}))) * list_sum(list_transform(range(({df} // 2)::BIGINT), lambda k: exp(lgamma(k + 0.5) - lgamma(k + 1)) / sqrt(pi()) * pow({c2}, k)))"
    return f"1 - CASE WHEN {df} % 2 = 1 THEN {odd} ELSE {even} END"


_RATES = "rt AS (SELECT {by}, avg((outcome = 'correct')::INTEGER) AS rate FROM an {where} GROUP BY ALL)"
ORACLES["rq1_retention"] = f"WITH {_ANS}, {_RATES.format(by='component, phase, condition, participant', where='')} SELECT component, phase, condition, {_ci('rate', 'users')} FROM rt GROUP BY ALL"
ORACLES["rq1_totals"] = f"WITH {_ANS} SELECT component, phase, condition, count(*) AS answers, sum((outcome = 'correct')::INTEGER)::BIGINT AS correct FROM an GROUP BY ROLLUP (component, phase, condition)"
ORACLES["rq1_answer_mix"] = f"""WITH {_ANS}, mx AS (SELECT component, phase, condition, participant, o AS outcome, avg((an.outcome = o)::INTEGER) AS share FROM an CROSS JOIN (VALUES ('correct'), ('incorrect'), ('unknown')) v(o) GROUP BY ALL)
SELECT component, phase, condition, outcome, mean AS share, lo, hi FROM (SELECT component, phase, condition, outcome, {_ci('share', 'users')} FROM mx GROUP BY ALL)"""


def _within(unit: str, by: str) -> str:
    return f"""WITH {_ANS}, {_RATES.format(by=f'{by}, {unit}, condition', where='')},
df AS (SELECT {', '.join('e.' + b.strip() for b in by.split(','))}, e.{unit}, o.condition AS versus, e.rate - o.rate AS diff FROM rt e JOIN rt o USING ({by}, {unit}) WHERE e.condition = 'embedded' AND o.condition <> 'embedded'),
tt AS (SELECT {by}, versus, count(*) AS n, avg(diff) AS m, CASE WHEN stddev_samp(diff) > 0 THEN avg(diff) / (stddev_samp(diff) / sqrt(count(*))) END AS t FROM df GROUP BY ALL)"""


def _tested(unit: str, by: str) -> str:
    return f"{_within(unit, by)} SELECT {by}, versus, n, round(m, 6) AS mean_diff, round(t, 6) AS t, n - 1 AS df, round({_p('t', '(n - 1)')}, 6) AS p FROM tt"


ORACLES["rq1_ttests"] = _tested("participant", "component, phase")
ORACLES["rq1_within_user"] = _tested("participant", "phase")
ORACLES["rq1_within_word"] = _tested("word", "phase")


def _box(unit: str) -> str:
    return f"""SELECT '{unit}' AS unit, phase, versus, round(min(diff) FILTER (diff >= q1 - 1.5 * (q3 - q1)), 6) AS lo_whisker, round(q1, 6) AS q1, round(median, 6) AS median, round(q3, 6) AS q3, round(max(diff) FILTER (diff <= q3 + 1.5 * (q3 - q1)), 6) AS hi_whisker, count(*) FILTER (diff < q1 - 1.5 * (q3 - q1) OR diff > q3 + 1.5 * (q3 - q1)) AS outliers
FROM (SELECT *, quantile_cont(diff, 0.25) OVER g AS q1, quantile_cont(diff, 0.5) OVER g AS median, quantile_cont(diff, 0.75) OVER g AS q3 FROM (SELECT phase, versus, round(diff, 9) AS diff FROM df) WINDOW g AS (PARTITION BY phase, versus)) GROUP BY phase, versus, q1, median, q3"""


ORACLES["rq1_boxplot"] = f"SELECT * FROM ({_within('participant', 'phase')} {_box('participant')}) UNION ALL SELECT * FROM ({_within('word', 'phase')} {_box('word')})"
ORACLES["rq2_click_histogram"] = f"WITH {_ANS}, hs AS (SELECT participant, clicks, count(*) / sum(count(*)) OVER (PARTITION BY participant) AS x FROM ck GROUP BY participant, clicks) SELECT clicks, round(sum(x) / (SELECT count(DISTINCT participant) FROM ck), 6) AS share FROM hs GROUP BY 1"
ORACLES["rq2_easiness_by_clicks"] = f"WITH {_ANS}, ez AS (SELECT word, avg((outcome = 'correct')::INTEGER) AS e FROM an WHERE component = 'mc' AND phase = 'short' AND condition <> 'embedded' GROUP BY 1) SELECT clicks, {_ci('e', 'cells')} FROM ck JOIN ez USING (word) GROUP BY 1"
ORACLES["rq2_retention_by_clicks"] = f"WITH {_ANS} SELECT clicks, phase, {_ci('ok', 'cells')} FROM (SELECT clicks, phase, (outcome = 'correct')::INTEGER::DOUBLE AS ok FROM an JOIN ck USING (participant, word) WHERE component = 'mc' AND condition = 'embedded') GROUP BY ALL"
_TIMES = f"{_EVENTS}, {_PAGES}, tm AS (SELECT (user_id % 58)::INTEGER AS participant, len(ws) AS words, value / 60 AS minutes, event_type = 'click' AS treated FROM ev CROSS JOIN np JOIN page_ws ON u = ((user_id % greatest(1, (n + 99) // 100)) * 100 + k % least(100, n)) % n WHERE event_type IN ('view', 'click') AND value > 0), sd AS (SELECT participant, treated, sum(words) / sum(minutes) AS wpm FROM tm GROUP BY ALL)"
ORACLES["rq3_speed"] = f"WITH {_TIMES} SELECT treated, count(*) AS users, round(quantile_cont(wpm, 0.5), 6) AS median_wpm, round(quantile_cont(wpm, 0.25), 6) AS q1, round(quantile_cont(wpm, 0.75), 6) AS q3 FROM sd GROUP BY 1"
ORACLES["rq3_overhead"] = f"""WITH {_TIMES}, md AS (SELECT quantile_cont(wpm, 0.5) FILTER (treated) AS a, quantile_cont(wpm, 0.5) FILTER (NOT treated) AS b FROM sd),
dt AS (SELECT sum(minutes) FILTER (treated) - sum(words) FILTER (treated) * sum(minutes) FILTER (NOT treated) / sum(words) FILTER (NOT treated) AS d FROM tm GROUP BY participant)
SELECT round(1 - a / b, 6) AS slowdown, round(b / a - 1, 6) AS overhead, (SELECT round(avg(d), 6) FROM dt) AS delta_minutes FROM md"""


def _arms(where: str) -> str:
    return f"""WITH {_ANS}, {_RATES.format(by='phase, arm, participant', where=where)},
tt AS (SELECT phase, count(*) AS n, avg(e.rate - r.rate) / (stddev_samp(e.rate - r.rate) / sqrt(count(*))) AS t FROM rt e JOIN rt r USING (phase, participant) WHERE e.arm = 'easy' AND r.arm = 'random' GROUP BY 1),
ci AS (SELECT phase, arm, {_ci('rate', 'users')} FROM rt GROUP BY ALL)
SELECT ci.*, round(t, 6) AS t, round({_p('t', '(n - 1)')}, 6) AS p FROM ci JOIN tt USING (phase)"""


ORACLES["rq4_context_effect"] = _arms("WHERE component = 'mc' AND condition = 'embedded'")
ORACLES["rq4_never_clicked"] = _arms("WHERE component = 'mc' AND condition = 'embedded' AND (participant, word) IN (SELECT (participant, word) FROM ck WHERE clicks = 0)")
_CODES = "cd AS (SELECT CASE WHEN doc_id % 2 = 0 THEN 'embedded' ELSE 'table' END AS arm, (quality = 1 OR toxic = 1)::INTEGER AS broad, (quality = 1 AND toxic = 1)::INTEGER AS narrow FROM labels)"
ORACLES["rq5_mnemonics"] = f"WITH {_CODES} SELECT arm, 'broad' AS coding, round(avg(broad), 6) AS share FROM cd GROUP BY 1 UNION ALL SELECT arm, 'narrow', round(avg(narrow), 6) FROM cd GROUP BY 1"
ORACLES["rq5_ratio"] = f"WITH {_CODES} SELECT round(avg(narrow) FILTER (arm = 'table') / avg(broad) FILTER (arm = 'embedded'), 6) AS ratio FROM cd"
_GUESS = f"""{_RUNS}, {_SHARES}, gp AS (SELECT sh.doc_id, sh.w, 0.0 * p3 + 0.7 * p2 + 0.3 * p1 AS g, quality::DOUBLE AS y FROM sh JOIN labels USING (doc_id) QUALIFY row_number() OVER (PARTITION BY sh.doc_id ORDER BY md5(concat_ws('|', '42', sh.doc_id, pos)), pos) = 1),
gr AS (SELECT 1.0::DOUBLE AS x0, ln(uni.n) AS x1, ln((SELECT count(*) FROM runs r WHERE r.doc_id = gp.doc_id AND r.w = gp.w) / (SELECT count(*) FROM runs r WHERE r.doc_id = gp.doc_id)) AS x2, ln(g) AS x3, y AS x4 FROM gp JOIN uni ON uni.w = gp.w)"""
ORACLES["guess_moments"] = f"WITH {_GUESS} " + " UNION ALL ".join(f"SELECT {i} AS i, {j} AS j, round(sum(x{i} * x{j}), 4) AS sum_xy FROM gr" for i in range(5) for j in range(i, 5))
# three standardized coefficients by Cramer's rule on the correlations
_CORR = ", ".join(f"corr(x{i}, x{j}) AS r{i}{j}" for i in range(1, 5) for j in range(i + 1, 5))
_DET = "(1 + 2 * r12 * r13 * r23 - r12 * r12 - r13 * r13 - r23 * r23)"
_BETAS = {"log_corpus": "r14 * (1 - r23 * r23) - r12 * (r24 - r23 * r34) + r13 * (r24 * r23 - r34)", "log_text": "(r24 - r23 * r34) - r14 * (r12 - r23 * r13) + r13 * (r12 * r34 - r24 * r13)", "log_g": "(r34 - r24 * r23) - r12 * (r12 * r34 - r24 * r13) + r14 * (r12 * r23 - r13)"}
ORACLES["guess_rank"] = f"WITH {_GUESS}, cr AS (SELECT {_CORR} FROM gr), bt AS (" + " UNION ALL ".join(f"SELECT '{k}' AS feature, ({v}) / {_DET} AS b FROM cr" for k, v in _BETAS.items()) + ") SELECT feature, round(b, 6) AS beta_std, (row_number() OVER (ORDER BY abs(b) DESC, feature))::INTEGER AS rank FROM bt"
