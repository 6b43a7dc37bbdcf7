"""DuckDB statements that compute the same rows as the registered queries.

They are put together from shared parts: tokens, windows, attention cells, raw scores, standard scores, choices.
"""

from __future__ import annotations

from farspan.operators.select import LADDER

WORD = r"[^\x20\x09-\x0D]+"
L, K = 128, 32


def tokens(table: str = "documents", key: str = "doc_id", category: str = "lang", text: str = "text") -> str:
    return f"""toks as (select {key} as doc_id, {category} as category, regexp_extract_all(coalesce({text}, ''), '{WORD}') as toks from {table}),
 tok as (select doc_id, category, toks, len(toks)::bigint as n from toks)"""


def starts(n: str, L: int) -> str:
    c = f"(({n} + {L} - 1) // {L})"
    return f"""case when {n} >= {L} then list_concat(list_concat(list_transform(range(0, {c} // 2), lambda j: j * {L}),
 case when {c} % 2 = 1 then [({n} - {L}) // 2] else [] end), list_transform(range(0, {c} // 2), lambda j: {n} - ({c} // 2 - j) * {L})) else [] end"""


def windows(L: int = L) -> str:
    return f"""cutting as (select doc_id, category, n, toks, {starts('n', L)} as s from tok),
 win as (select doc_id, category, n, unnest(range(len(s))) as ord, unnest(s)::bigint as start, toks, len(s) as c from cutting)"""


def cells(L: int = L, K: int = K, source: str = "win") -> str:
    return f"""wt as (select doc_id, category, start, unnest(range(1, {L} + 1)) as q, unnest(list_slice(toks, start + 1, start + {L})) as tok from {source}),
 vec as (select tok, list_transform(range(1, 17), lambda j: (instr('0123456789abcdef', substr(md5(tok), j::int, 1)) - 8.5) / 4.6) as v from (select distinct tok from wt)),
 wv as materialized (select doc_id, category, start, q, v from wt join vec using (tok)),
 cell as (select a.doc_id, a.category, a.start, a.q, b.q as i, exp(list_dot_product(a.v, b.v) / 4.0) as w from wv a join wv b on a.doc_id = b.doc_id and a.start = b.start and b.q <= a.q),
 row_stat as materialized (select doc_id, category, start, q, sum(w) as tot, coalesce(sum(w) filter (i <= q - {K}), 0) as f, coalesce(sum(w * w) filter (i <= q - {K}), 0) as s2, max(w) filter (i = 1) as w1 from cell group by all)"""


def raw(L: int = L, K: int = K) -> str:
    n = (L - K) * (L - K + 1) // 2
    return f"""raw as materialized (select doc_id, category, start, {L} as len, sum(f / tot) / {L} as ds, sum(f / tot) as fs, sum(s2 / (tot * tot)) as ss,
 -(sum(s2 / (tot * tot)) / {n} - (sum(f / tot) / {n}) * (sum(f / tot) / {n})) as du, sum(w1 / tot) / {L} as sink from row_stat group by all)"""


def lds(alpha: float = 0.5, by: str = "") -> str:
    over = f"over (partition by {by})" if by else "over ()"
    return f"""zs as (select *, case when stddev_pop(ds) {over} > 0 then (ds - avg(ds) {over}) / stddev_pop(ds) {over} else 0 end as ds_z,
 case when stddev_pop(du) {over} > 0 then (du - avg(du) {over}) / stddev_pop(du) {over} else 0 end as du_z from raw),
 lds as (select *, ds_z + {alpha} * du_z as lds from zs)"""


def quota(wanted: str, source: str, into: str = "quota") -> str:
    """Largest remainders of wanted over the categories of source."""
    return f"""{into}_c as (select category, count(*)::bigint as c, sum(count(*)) over ()::bigint as t from {source} group by category),
 {into}_f as (select category, c, ({wanted}) * c // t as fl, ({wanted}) * c % t as rem, ({wanted}) as w from {into}_c),
 {into} as (select category, least(c, fl + case when row_number() over (order by rem desc, category) <= w - sum(fl) over () then 1 else 0 end) as quota from {into}_f)"""


def with_(*parts: str) -> str:
    return "with " + ",\n ".join(parts) + "\n"


BASE = (tokens(), windows())
SCORED = (*BASE, cells(), raw())
RANKED = (*SCORED, lds())
UNIT = f"((select count(*) from win) * {L} // 40)"


def wanted(step: int) -> str:
    return f"({step} * {UNIT} // {L})"


def choice(step: int, order: str, source: str, name: str) -> str:
    """Rows of source up to the quota of a step, as relation ``name``."""
    return quota(wanted(step), source, f"q_{name}") + f""",
 r_{name} as (select *, row_number() over (partition by category order by {order}) as rnk from {source}),
 {name} as (select r.* from r_{name} r join q_{name} q using (category) where rnk <= q.quota)"""


BY_LDS = "round(lds, 6) desc, doc_id, start"
BY_HASH = "md5(concat_ws(':', '7', doc_id::varchar, start::varchar)), doc_id, start"


def ladder(source: str, order: str, method: str) -> str:
    parts = ",\n ".join(quota(wanted(s), source, f"q{s}_{method}") for s in LADDER)
    joins = " ".join(f"join q{s}_{method} using (category)".replace("using (category)", f"on q{s}_{method}.category = r.category") for s in LADDER)
    step = "case " + " ".join(f"when rnk <= q{s}_{method}.quota then {s}" for s in LADDER) + " end"
    return parts + f""",
 l_{method} as (select '{method}' as method, ({step})::int as step, r.category, r.doc_id, r.start, {L} as len, rnk from (select *, row_number() over (partition by category order by {order}) as rnk from {source}) r {joins} where {step} is not null)"""


SEG, BETA = 32, 0.3


def segment_scores() -> str:
    m = L // SEG
    return f"""bag as (select doc_id, category, start, tok, (q - 1) // {SEG} as s, count(*) as c from wt group by all),
 bg as (select tok, (count(*) + 1) / ((select count(*) from wt) + (select count(distinct tok) from wt))::double as p0 from wt group by tok),
 seg as (select * from bag join bg using (tok)),
 alone as (select doc_id, category, start, s, sum(c * ln(p0)) as l0 from seg group by all),
 shared as (select a.doc_id, a.start, a.s as si, b.s as sj, sum(a.c * ln(1 + b.c * {BETA} / (a.p0 * {SEG} * (1 - {BETA})))) as g from seg a join bag b on a.doc_id = b.doc_id and a.start = b.start and a.tok = b.tok and b.s < a.s group by all),
 pair as (select x.doc_id, x.category, x.start, x.s as si, y.s as sj, x.l0, coalesce(g, 0) as g from alone x join alone y on x.doc_id = y.doc_id and x.start = y.start and y.s < x.s left join shared h on h.doc_id = x.doc_id and h.start = x.start and h.si = x.s and h.sj = y.s),
 gain as (select *, greatest(0, 1 - exp(-(l0 + {SEG} * ln(1 - {BETA}) + g) / {SEG}) / exp(-l0 / {SEG})) * (si - sj) / {m} as v from pair),
 spb as (select doc_id, category, start, {L} as len, avg(v) as spb from gain group by all)"""


WT = f"wt as (select doc_id, category, start, unnest(range(1, {L} + 1)) as q, unnest(list_slice(toks, start + 1, start + {L})) as tok from win)"

ORACLES: dict[str, str] = {
    "doc_tokens": with_(tokens()) + "select doc_id, category, n from tok",
    "window_spans": with_(*BASE) + "select doc_id, category, n, ord::int as ord, start from win",
    "window_spans_char32k": f"with t as (select doc_id, lang as category, length(text)::bigint as n from documents), c as (select *, {starts('n', 32768)} as s from t) select doc_id, category, n, unnest(range(len(s)))::int as ord, unnest(s)::bigint as start from c",
    "window_branch_counts": with_(tokens()) + f"select category, case when n < {L} then 'short' when n = {L} then 'one' when n <= 2 * {L} then 'two' when n <= 3 * {L} then 'three' else 'peeled' end as branch, count(*) as documents, sum(case when n >= {L} then (n + {L} - 1) // {L} else 0 end)::bigint as windows from tok group by all",
    "window_coverage": with_(tokens()) + f"select doc_id, n, (n + {L} - 1) // {L} as windows, true as covered, (n + {L} - 1) // {L} * {L} - n as overlap, true as distinct_starts from tok where n >= {L}",
    "naive_truncate": with_(tokens()) + f"select doc_id, category, md5(array_to_string(list_slice(toks, 1, {L}), ' ')) as h from tok where n >= {L}",
    "stride_windows": with_(tokens()) + f"select doc_id, unnest(range(0, n - {L} + 1, 64))::bigint as start from tok where n >= {L}",
    "concat_pack": with_(tokens())
    + f""", shorts as (select *, md5(concat_ws(':', '7', doc_id::varchar)) as key from tok where n < {L} and n > 0),
 dealt as (select *, (('0x' || substr(key, 1, 8))::bigint % greatest(16, ((select count(*) from shorts) + 99999) // 100000))::int as bucket from shorts),
 placed as (select *, sum(n) over (partition by category, bucket order by key, doc_id) - n as b from dealt),
 flat as (select category, bucket, (b + i)::bigint as pos, toks[i + 1] as tok from (select *, unnest(range(n)) as i from placed))
 select category, bucket, (pos // {L})::bigint as bin, md5(string_agg(tok, ' ' order by pos)) as h from flat group by category, bucket, pos // {L} having count(*) = {L}""",
    "attention_scores": with_(*SCORED) + "select doc_id, category, start, round(ds * 1e6)::bigint as ds_e6, round(du * 1e9)::bigint as du_e9, round(sink * 1e6)::bigint as sink_e6 from raw",
    "attention_multi_k": with_(*BASE, cells())
    + ", by_k as (select doc_id, start, k, sum(case when i <= q - k then w / tot else 0 end) as fs, sum(case when i <= q - k then (w / tot) * (w / tot) else 0 end) as ss from cell join row_stat using (doc_id, category, start, q), (select unnest([16, 32, 64])::int as k) group by all), "
    + f"sc as (select k, fs / {L} as ds, ({L} - k) * ({L} - k + 1) / 2 as n, fs, ss from by_k) select k, count(*) as windows, round(avg(ds), 6) as ds, round(avg(-(ss / n - (fs / n) * (fs / n))), 9) as du from sc group by k",
    "token_strength": with_(*BASE, cells()) + "select doc_id, start, q::int as q, round(f / tot * 1e6)::bigint as ds_e6 from row_stat",
    "attention_variants": with_(*SCORED)
    + f"""select r.doc_id, r.start, round(r.ss * 0 - (r.ss / {(L - K) ** 2} - (r.fs / {(L - K) ** 2}) * (r.fs / {(L - K) ** 2})) * 1e9)::bigint as square_e9,
 round(-t.v * 1e9)::bigint as token_e9, round(r.du * {(L - K) * (L - K + 1) // 2}::double / {(L - K) * (L - K + 1) // 2 - 1} * 1e9)::bigint as sample_e9
 from raw r join (select doc_id, start, var_pop(f / tot) as v from row_stat group by all) t using (doc_id, start)""",
    "score_moments": with_(*SCORED) + "select 'global' as scope, count(*) as n, round(avg(ds), 6) as ds_mean, round(stddev_pop(ds), 6) as ds_sd, round(avg(du), 9) as du_mean, round(stddev_pop(du), 9) as du_sd from raw union all select category, count(*), round(avg(ds), 6), round(stddev_pop(ds), 6), round(avg(du), 9), round(stddev_pop(du), 9) from raw group by category",
    "lds_scores": with_(*RANKED) + "select doc_id, category, start, round(ds_z, 5) as ds_z, round(du_z, 5) as du_z, round(lds, 5) as lds from lds",
    "lds_scores_by_category": with_(*SCORED, lds(0.5, "category")) + "select doc_id, category, start, round(lds, 5) as lds from lds",
    "score_magnitudes": with_(*RANKED)
    + " union all ".join(f"select '{x}' as score, count(*) as n, round(min({x}), 8) as low, round(quantile_cont({x}, 0.25), 8) as q1, round(quantile_cont({x}, 0.5), 8) as mid, round(quantile_cont({x}, 0.75), 8) as q3, round(max({x}), 8) as high, round(stddev_pop({x}), 8) as sd from lds" for x in ("ds", "du", "ds_z", "du_z")),
    "alpha_sweep": with_(*RANKED) + "select alpha, count(*) as windows, case when round(avg(ds_z + alpha * du_z), 6) = 0 then 0.0 else round(avg(ds_z + alpha * du_z), 6) end as mean_lds, round(stddev_pop(ds_z + alpha * du_z), 6) as sd_lds, round(max(ds_z + alpha * du_z), 5) as best_lds from lds, (select unnest([0.0, 0.25, 0.5, 1.0, 2.0])::double as alpha) group by alpha",
    "select_top_budget": with_(*RANKED, choice(5, BY_LDS, "lds", "best")) + f"select 'attention' as method, 5 * {UNIT} as budget_tokens, category, doc_id, start, rnk, rnk * {L} as cum_tokens from best",
    "select_by_threshold": with_(*RANKED, choice(5, BY_LDS, "lds", "best")) + "select category, doc_id, start from best",
    "select_no_category": with_(*RANKED) + f"select doc_id, start, row_number() over (order by {BY_LDS}) as rnk from lds qualify rnk <= {wanted(5)}",
    "select_random": with_(*BASE, choice(5, BY_HASH, "win", "best")) + "select category, doc_id, start, rnk from best",
    "select_ladder": with_(*RANKED, ladder("lds", BY_LDS, "attention")) + "select * from l_attention",
    "random_ladder": with_(*BASE, ladder("win", BY_HASH, "random")) + "select * from l_random",
    "spb_scores": with_(*BASE, WT, segment_scores()) + "select doc_id, category, start, round(spb, 6) as spb from spb",
    "spb_parts": with_(*BASE, WT, segment_scores())
    + f", both_ as (select doc_id, start, greatest(0, 1 - exp(-(l0 + {SEG} * ln(1 - {BETA}) + g) / {SEG}) / exp(-l0 / {SEG})) as gain, (si - sj) / {L // SEG} as dist from pair) select doc_id, start, round(avg(gain), 6) as gain, round(avg(dist), 6) as dist, round(avg(gain + dist), 6) as both from both_ group by doc_id, start",
    "clean_documents": "with t as (select doc_id, lang as category, coalesce(text, '') as text from documents), k as (select * from t where regexp_matches(text, '[^\\x20\\x09-\\x0D]') and length(regexp_replace(text, '[\\p{L}\\p{N}\\s]', '', 'g')) <= 0.3 * length(text)) select min(doc_id) as doc_id from k group by md5(text)".replace("\\\\", "\\"),
    "select_spb": with_(*BASE, WT, segment_scores(), choice(5, "round(spb, 6) desc, doc_id, start", "spb", "best")) + "select category, doc_id, start, rnk from best",
    "linguistic_metrics": with_(*BASE, WT)
    + f""", pw as (select doc_id, category, start, tok, count(*) / {L}.0 as p from wt group by all),
 whole as (select doc_id, category, start, count(*) / {L}.0 as type_token, sum(-p * ln(p)) as entropy from pw group by all),
 uw as (select doc_id, start, (q - 1) // 32 as u, tok, count(*) as c from wt group by all),
 nm as (select doc_id, start, u, sqrt(sum(c * c)) as norm, count(*) as types from uw group by all),
 met as (select a.doc_id, a.start, a.u, sum(a.c * b.c) as dot, count(*) as common from uw a join uw b on a.doc_id = b.doc_id and a.start = b.start and a.tok = b.tok and b.u = a.u - 1 group by all),
 near as (select a.doc_id, a.start, avg(coalesce(m.dot / (a.norm * b.norm), 0)) as coherence, avg(coalesce(m.common / a.types::double, 0)) as cohesion from nm a join nm b on a.doc_id = b.doc_id and a.start = b.start and b.u = a.u - 1 left join met m on m.doc_id = a.doc_id and m.start = a.start and m.u = a.u group by all)
 select w.doc_id, w.category, w.start, round(type_token, 6) as type_token, round(entropy, 6) as entropy, round(coalesce(coherence, 0), 6) as coherence, round(coalesce(cohesion, 0), 6) as cohesion from whole w left join near using (doc_id, start)""",
    "label_rates": with_(*RANKED, ladder("lds", BY_LDS, "attention"), ladder("win", BY_HASH, "random"))
    + ", both_ as (select * from l_attention union all select * from l_random), steps as (select b.method, s.step, b.doc_id, b.start from both_ b join (select unnest([1, 3, 5, 10, 20])::int as step) s on b.step <= s.step) select method, step, count(*) as windows, count(quality) as labelled, round(avg(quality), 6) as good, round(avg(toxic), 6) as toxic from steps left join labels using (doc_id) group by method, step",
    "selection_agreement": with_(*RANKED, choice(5, BY_LDS, "lds", "a"), choice(5, BY_HASH, "win", "b"))
    + ", both_ as (select a.doc_id as x, b.doc_id as y from a full outer join b on a.doc_id = b.doc_id and a.start = b.start) select count(*) filter (x is not null and y is not null) as common, count(*) as either, round(count(*) filter (x is not null and y is not null) / count(*)::double, 9) as jaccard from both_",
    "alpha_ablation": with_(*RANKED, choice(3, BY_LDS, "lds", "b3"), choice(5, BY_LDS, "lds", "b5"), "l0 as (select * exclude (lds), ds_z as lds from lds)", "l1 as (select * exclude (lds), ds_z + du_z as lds from lds)", choice(3, BY_LDS, "l0", "n3"), choice(5, BY_LDS, "l0", "n5"), choice(3, BY_LDS, "l1", "o3"), choice(5, BY_LDS, "l1", "o5"))
    + " union all ".join(
        f"select {s} as step, '{name}' as variant, (select count(*) from {rel}) as windows, (select count(*) from {rel} x join b{s} y on x.doc_id = y.doc_id and x.start = y.start) as kept, round((select avg(ds_z) from {rel}), 5) as mean_ds_z, round((select avg(du_z) from {rel}), 5) as mean_du_z, round((select avg(quality) from {rel} join labels using (doc_id)) - (select avg(quality) from b{s} join labels using (doc_id)), 6) as good_delta"
        for s in (3, 5)
        for name, rel in (("alpha_0.5", f"b{s}"), ("alpha_1", f"o{s}"), ("no_uniformity", f"n{s}"))
    ),
    "diversity": with_(*RANKED, choice(5, BY_LDS, "lds", "a"), choice(5, BY_HASH, "win", "b"))
    + f""", picks as (select 'attention' as method, doc_id, start from a union all select 'random', doc_id, start from b),
 pt as (select p.method, p.doc_id, w.category, p.start, list_slice(w.toks, p.start + 1, p.start + {L}) as toks from picks p join win w using (doc_id, start)),
 words as (select method, unnest(toks) as tok from pt),
 marks as (select distinct method, doc_id, start, g from (select method, doc_id, start, md5(array_to_string(list_slice(toks, i, i + 7), ' ')) as g from (select *, unnest(range(1, {L} - 6)) as i from pt)) where ends_with(g, '0')),
 again as (select method, doc_id, start, avg(case when row(doc_id, start) <> f then 1 else 0 end) as again from (select *, min(row(doc_id, start)) over (partition by method, g) as f from marks) group by all),
 big as (select method, max(n) / sum(n) as largest from (select method, category, count(*) as n from pt group by all) group by method)
 select method, count(*) as windows, count(distinct doc_id) as documents, count(distinct md5(array_to_string(toks, ' '))) as distinct_windows, (select count(distinct tok) from words x where x.method = pt.method) as types, (select count(*) from words x where x.method = pt.method) as tokens,
 round((select largest from big where big.method = pt.method), 6) as largest_category, round((select count(*) from again x where x.method = pt.method and x.again >= 0.5) / count(*), 6) as near_copies from pt group by method""",
    "cost_model": with_(*BASE)
    + """, n as (select count(*)::bigint as windows from win), m as (select model, d::bigint as d, heads::bigint as heads, kv::bigint as kv, width::bigint as width from (values ('small', 128, 4, 2, 32), ('large', 512, 8, 2, 64)) t(model, d, heads, kv, width)),
 c as (select model, windows, heads * width * 128 * 129 // 2 + 128 * d * width * (heads + kv) as ops from m, n)
 select 'attention' as method, model, windows, windows as model_calls, windows * 128 as token_evaluations, round(ops::double * windows)::bigint as multiplications, 1 / 32.0 as share_of_pass from c
 union all select 'segments', model, windows, windows * 6, windows * 512, round((ops * 32 * 512 // 128)::double * windows)::bigint, 1.0 from c""",
    "conversation_scores": with_("dlg as (select conv_id, string_agg(coalesce(text, ''), ' ' order by turn, role, text) as text from conversations group by conv_id)", tokens("dlg", "conv_id", "'dialogue'"), windows(), cells(), raw()) + "select doc_id, start, round(ds * 1e6)::bigint as ds_e6, round(du * 1e9)::bigint as du_e9 from raw",
    "event_sequence_scores": f"with seq as (select user_id as doc_id, 'events' as category, list(event_type order by ts, event_id) as toks, count(*)::bigint as n from events where user_id is not null group by user_id), {windows(8).replace('from tok)', 'from seq)')}, {cells(8, 2)}, {raw(8, 2)} select doc_id, start, round(ds * 1e6)::bigint as ds_e6, round(du * 1e9)::bigint as du_e9 from raw",
    "vector_attention": """with s as (select label as doc_id, row_number() over (partition by label order by vec_id) as q, embedding::double[] as v, count(*) over (partition by label) as n from embeddings),
 cell as (select a.doc_id, a.q, b.q as i, a.n, exp(list_dot_product(a.v, b.v) / 8.0) as w from s a join s b on a.doc_id = b.doc_id and b.q <= a.q),
 r as (select doc_id, n, q, sum(w) as t, coalesce(sum(w) filter (i <= q - n // 4), 0) as f from cell group by all)
 select doc_id::bigint as doc_id, n::int as len, round(sum(f / t) / max(n) * 1e6)::bigint as ds_e6 from r group by doc_id, n""",
    "page_windows": with_(
        r"""page as (select page_id, replace(replace(replace(replace(replace(regexp_replace(regexp_replace(html, '(?s)<!--.*?-->|<(script|style)[^>]*>.*?</(script|style)>', ' ', 'g'), '<[^>]*>', ' ', 'g'), '&lt;', '<'), '&gt;', '>'), '&quot;', '"'), '&nbsp;', ' '), '&amp;', '&') as text from pages)""",
        tokens("page", "page_id", "'page'"),
        windows(),
    )
    + "select doc_id, n, count(*) as windows, sum(start)::bigint as start_sum from win group by doc_id, n",
    "benchmark_overlap": """with words as (select doc_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') as w from documents), items as (select item_id, regexp_extract_all(coalesce(text, ''), '[^\\x20\\x09-\\x0D]+') as w from benchmark),
 dg as (select distinct doc_id, array_to_string(list_slice(w, i, i + 7), ' ') as g from (select doc_id, w, unnest(range(1, len(w) - 6)) as i from words)), ig as (select distinct item_id, array_to_string(list_slice(w, i, i + 7), ' ') as g from (select item_id, w, unnest(range(1, len(w) - 6)) as i from items))
 select item_id, doc_id, count(*) as shared from dg join ig using (g) group by all""".replace("\\\\", "\\"),
    "planted_auc": with_(*BASE)
    + f""", keyed as (select doc_id, category, start, list_slice(toks, start + 1, start + {L}) as tk, md5(concat_ws(':', '7', doc_id::varchar, start::varchar)) as key from win),
 nxt as (select *, coalesce(lead(tk) over (partition by category order by key, doc_id, start), first_value(tk) over (partition by category order by key, doc_id, start)) as other from keyed),
 made as (select doc_id, category, start * 2 + label as start, label, list_concat(list_slice(tk, 1, {L} - 32), list_slice(case when label = 1 then tk else other end, 1, 32)) as toks from nxt, (select unnest([0, 1]) as label) where other is not null),
 """
    + cells(source="made").replace(f"list_slice(toks, start + 1, start + {L})", "toks")
    + ",\n "
    + raw()
    + """, x as (select round(ds, 9) as x, (start % 2)::bigint as y from raw), per as (select x, sum(y) as p, sum(1 - y) as n from x group by x),
 w as (select p, n, p * (coalesce(sum(n) over (order by x rows between unbounded preceding and 1 preceding), 0) + n / 2) as won from per)
 select sum(p)::bigint as positives, sum(n)::bigint as negatives, round(sum(won) / (sum(p) * sum(n)), 6) as auc from w""",
    "cells_reference": with_(tokens(), windows(32), cells(32, 8), raw(32, 8)) + "select doc_id, start, round(ds * 1e6)::bigint as ds_e6, round(fs / 32 * 1e6)::bigint as ds_block_e6, round(du * 1e9)::bigint as du_e9, 0::bigint as off_e9 from raw",
    "cumulative_attention": with_(tokens(), windows(32), cells(32, 8)) + "select m::int as m, round(avg(a) * 1e6)::bigint as mean_e6, count(*) as rows from (select doc_id, start, q, i as m, sum(w) over (partition by doc_id, start, q order by i) / sum(w) over (partition by doc_id, start, q) as a from cell) where q = 32 group by m",
    "document_rollup": with_(*RANKED) + "select doc_id, category, count(*) as windows, round(avg(lds), 5) as mean_lds, round(max(lds), 5) as best_lds from lds group by doc_id, category",
    "mix_short": with_(*BASE, choice(5, BY_HASH, "win", "best"))
    + f""", sh as (select category, doc_id, n, md5(concat_ws(':', '7', doc_id::varchar)) as key from tok where n < {L} and n > 0), up as (select *, sum(n) over (order by key, doc_id) as upto from sh)
 select category, doc_id, start, {L} as len, 'long' as kind from best union all select category, doc_id, 0, n::int, 'short' from up where upto <= floor(0.1 * (select count(*) * {L} from best))""",
}


def scale_cells() -> str:
    """Long table of method x budget with the stand-in measures, from all three rankings."""
    return with_(*RANKED, segment_scores(), ladder("lds", BY_LDS, "attention"), ladder("win", BY_HASH, "random"), ladder("spb", "round(spb, 6) desc, doc_id, start", "segments")) + """, both_ as (select * from l_attention union all select * from l_random union all select * from l_segments),
 steps as (select b.method, s.step, b.doc_id, b.start from both_ b join (select unnest([1, 3, 5, 10, 20])::int as step) s on b.step <= s.step where s.step <= 10 or b.method = 'random')
 select method, step, count(*) as windows, round(avg(z.ds_z), 5) as mean_ds_z, round(avg(quality), 6) as good, round(avg(toxic), 6) as toxic, count(distinct steps.doc_id) as documents
 from steps join lds z using (doc_id, start) left join labels using (doc_id) group by method, step"""


def scale_sizes() -> str:
    """Sizes of all sets of the data-scale comparison, from the quotas alone."""
    sizes = " union all ".join(f"select {s}::int as step, sum(quota)::bigint as windows, sum(quota)::bigint * {L} as tokens, count(*) filter (quota > 0) as categories, max(quota)::bigint as deepest_rank from q{s}" for s in LADDER)
    return with_(*BASE, *[quota(wanted(s), "win", f"q{s}") for s in LADDER]) + f", sizes as ({sizes}) select method, step, windows, tokens, categories, deepest_rank from sizes, (select unnest(['random', 'segments', 'attention_small', 'attention_large']) as method) where step <= 10 or method = 'random'"


def sampled_rows(rows: int) -> list[int]:
    """Rows (from 1) that the estimator computes: the middles of equal strata of those that can look far."""
    import numpy as np

    edges = np.linspace(K, L, min(rows, L - K) + 1)
    return (np.unique(((edges[:-1] + edges[1:]) / 2).astype(int)) + 1).tolist()


def sampled_scores(rows: int = 24) -> str:
    at = sampled_rows(rows)
    r = len(at)
    return with_(*SCORED) + f""", own as (select doc_id, start, q, f / tot as f, f / tot - lag(f / tot) over (partition by doc_id, start order by q) as step from row_stat where q in ({", ".join(map(str, at))})),
 est as (select doc_id, start, {L - K} / {L}.0 * avg(f) as ds_hat, {L - K} / {L}.0 * sqrt(coalesce(sum(step * step), 0) / 2 / {max(1, r - 1)} / {r}) as se from own group by all),
 met as (select est.*, ds_hat - ds as off from est join raw using (doc_id, start))
 select count(*) as windows, round(sqrt(avg(off * off)), 6) as rmse, round(avg(off), 6) as bias, round(avg(case when abs(off) <= 2 * se then 1 else 0 end), 6) as within_2se from met"""


def proxy(name: str, picked: str, held: str) -> str:
    """Relation ``out_<name>``: the proxy model fitted on the windows of one relation (doc_id, start, tk), judged on another."""
    flat = lambda rel: f"select doc_id, start, i, tk[i + 1] as tok, case when i > 0 then tk[i] end as prev from (select *, unnest(range(len(tk))) as i from {rel})"
    classed = lambda rel: f"select x.*, k.p, coalesce(k.tok, ' ') as now_, case when x.prev is not null then coalesce(h.tok, ' ') end as last_ from {rel} x left join kn_{name} k on k.tok = x.tok left join kn_{name} h on h.tok = x.prev"
    return f"""fl_{name} as materialized ({flat(picked)}),
 kn_{name} as (select tok, c / ((select count(*) from fl_{name}) + 1)::double as p from (select tok, count(*) as c from fl_{name} group by tok order by c desc, tok limit 2000)),
 bi_{name} as (select last_, now_, count(*) as n2 from ({classed(f"fl_{name}")}) where last_ is not null group by all),
 he_{name} as (select last_, sum(n2) as n1 from bi_{name} group by last_),
 la_{name} as (select greatest(0.01, least(0.5, avg(case when i - m >= {K} then 1 else 0 end))) as lam from (select i, min(i) over (partition by doc_id, start, tok) as m from fl_{name})),
 hf_{name} as ({flat(held)}),
 hc_{name} as (select *, count(*) over (partition by doc_id, start, tok order by i range between unbounded preceding and {K} preceding) as seen from ({classed(f"hf_{name}")})),
 hp_{name} as (select c.i, coalesce(p, (select 1 - sum(p) from kn_{name})) as one, n1, coalesce(n2, 0) as n2, case when i >= {K} then seen / greatest(1, i - {K} + 1)::double else 0 end as cache, case when i >= {K} then lam else 0 end as w, lam from hc_{name} c left join bi_{name} b on b.last_ = c.last_ and b.now_ = c.now_ left join he_{name} h on h.last_ = c.last_, la_{name}),
 out_{name} as (select '{name}' as method, round(avg(-ln(greatest((1 - w) * case when n1 is not null then 0.5 * one + 0.5 * n2 / n1::double else one end + w * cache, 1e-12))), 6) as nats, count(*) as tokens, round(max(w), 6) as far_rate from hp_{name})"""


def proxy_rows(held: str) -> str:
    cut = f"wtk as materialized (select doc_id, start, list_slice(toks, start + 1, start + {L}) as tk from win)"
    chosen = ",\n ".join(f"p_{n} as (select wtk.* from wtk join {r} using (doc_id, start))" for n, r in (("attention", "a"), ("random", "b")))
    return with_(*RANKED, choice(5, BY_LDS, "lds", "a"), choice(5, BY_HASH, "win", "b"), cut, chosen, held, proxy("attention", "p_attention", "held"), proxy("random", "p_random", "held")) + "select * from out_attention union all select * from out_random"


def second_order() -> str:
    """Segment scores with pairs of neighbours as units, against the counts of all pairs."""
    return (
        with_(*BASE, WT)
        + f""", pw as (select *, (q - 1) // {SEG} as s, lag(tok) over (partition by doc_id, start order by q) as prev from wt),
 cnt as (select prev || chr(1) || tok as u, count(*) as c from pw where prev is not null group by all),
 sz as (select sum(c) as n, count(*) as v from cnt),
 bag as (select doc_id, category, start, s, case when (q - 1) % {SEG} = 0 then '' else prev end || chr(1) || tok as u, count(*) as c from pw group by all),
 seg as (select bag.*, (coalesce(cnt.c, 0) + 1) / (n + v)::double as p0 from bag left join cnt using (u), sz),
 shared as (select a.doc_id, a.start, a.s as si, b.s as sj, sum(a.c * ln(1 + b.c * {BETA} / (a.p0 * {SEG} * (1 - {BETA})))) as g from seg a join bag b on a.doc_id = b.doc_id and a.start = b.start and a.u = b.u and b.s < a.s group by all),
 each as (select doc_id, category, start, unnest(range(0, {L // SEG})) as si from win),
 pair as (select x.*, y.si as sj, coalesce(g, 0) as g from each x join each y on x.doc_id = y.doc_id and x.start = y.start and y.si < x.si left join shared h on h.doc_id = x.doc_id and h.start = x.start and h.si = x.si and h.sj = y.si)
 select doc_id, category, start, {L} as len, round(avg(greatest(0, 1 - exp(-({SEG} * ln(1 - {BETA}) + g) / {SEG})) * (si - sj) / {L // SEG}), 6) as spb, count(*) as model_calls from pair group by all"""
    )


def units() -> str:
    """Coherence and cohesion over sentences and over paragraphs."""
    text = "regexp_replace(coalesce(text, ''), '([^\\x20\\x09-\\x0D])[\\x20\\x09-\\x0D]*\\n[\\x20\\x09-\\x0D]*', '\\1\u2029 ', 'g')"
    ends = {"sentences": "regexp_matches(rtrim(tok, '\u2029'), '[.!?\u2026][\"'')\\]\u00bb\u201d\u2019]*$')", "paragraphs": "ends_with(tok, '\u2029')"}
    parts = []
    for name, end in ends.items():
        parts.append(f"""u_{name} as (select doc_id, start, rtrim(tok, '\u2029') as tok, coalesce(sum(case when {end} then 1 else 0 end) over (partition by doc_id, start order by q rows between unbounded preceding and 1 preceding), 0) as u from wt),
 c_{name} as (select doc_id, start, u, tok, count(*) as c from u_{name} group by all),
 n_{name} as (select doc_id, start, u, sqrt(sum(c * c)) as norm, count(*) as types from c_{name} group by all),
 m_{name} as (select a.doc_id, a.start, a.u, sum(a.c * b.c) as dot, count(*) as common from c_{name} a join c_{name} b on a.doc_id = b.doc_id and a.start = b.start and a.tok = b.tok and b.u = a.u - 1 group by all),
 r_{name} as (select a.doc_id, a.start, avg(coalesce(dot / (a.norm * b.norm), 0)) as coherence, avg(coalesce(common / a.types::double, 0)) as cohesion from n_{name} a join n_{name} b on a.doc_id = b.doc_id and a.start = b.start and b.u = a.u - 1 left join m_{name} m on m.doc_id = a.doc_id and m.start = a.start and m.u = a.u group by all),
 o_{name} as (select '{name}' as units, x.doc_id, x.start, x.n_units, round(coalesce(coherence, 0), 6) as coherence, round(coalesce(cohesion, 0), 6) as cohesion from (select doc_id, start, count(*) as n_units from n_{name} group by all) x left join r_{name} using (doc_id, start))""")
    return with_(f"marked as (select doc_id, lang, {text} as text from documents)", tokens("marked"), windows(), WT, *parts) + "select * from o_sentences union all select * from o_paragraphs"


_HELD = "used as (select doc_id from a union select doc_id from b), hashed as (select *, md5(array_to_string(tk, ' ')) as h from wtk), held as (select doc_id, start, tk from hashed where doc_id not in (select doc_id from used) and h not in (select h from hashed where doc_id in (select doc_id from used)))"
_ROBUST = "mid as (select quantile_disc(ds, 0.5) as ds_m, quantile_disc(du, 0.5) as du_m from raw), mad as (select 1.4826 * quantile_disc(abs(ds - ds_m), 0.5) as ds_s, 1.4826 * quantile_disc(abs(du - du_m), 0.5) as du_s from raw, mid)"
_FRONT = f"pre as (select doc_id, category, start, list_concat(['<s>'], list_slice(toks, start + 1, start + {L})) as toks from win)"

ORACLES["scale_grid_hexdot"] = scale_cells()
ORACLES["scale_grid"] = scale_sizes()
ORACLES["fixed_scale"] = "select * from (" + scale_sizes() + ") where step = 5 or (method = 'random' and step in (10, 20))"
ORACLES["score_sampled"] = sampled_scores()
ORACLES["lds_scores_robust"] = with_(*SCORED, _ROBUST) + "select doc_id, category, start, round(case when ds_s > 0 then (ds - ds_m) / ds_s else 0 end + 0.5 * case when du_s > 0 then (du - du_m) / du_s else 0 end, 5) as lds from raw, mid, mad"
ORACLES["spb_scores_pairs_order2"] = second_order()
ORACLES["proxy_lm"] = proxy_rows(_HELD)
ORACLES["short_guard"] = proxy_rows(f"held as (select doc_id, 0::bigint as start, toks as tk from tok where n < {L} and n >= 8)")
ORACLES["linguistic_units"] = units()
ORACLES["select_random_threshold"] = with_(*BASE, choice(5, BY_HASH, "win", "best")) + "select category, doc_id, start from best"
ORACLES["distinct_token_counts"] = with_(*BASE) + f"select category, sum((n + {L} - 1) // {L})::bigint as windows, sum((n + {L} - 1) // {L} * {L})::bigint as tokens, sum(n)::bigint as distinct from tok where n >= {L} group by category".replace("as distinct", 'as "distinct"')
ORACLES["front_token_scores"] = with_(*BASE, _FRONT, cells(L + 1, K, "pre").replace(f"list_slice(toks, start + 1, start + {L + 1})", "toks"), raw(L + 1, K)) + "select doc_id, category, start, len, round(ds * 1e6)::bigint as ds_e6, round(du * 1e9)::bigint as du_e9, round(sink * 1e6)::bigint as sink_e6 from raw"
ORACLES["cost_ratios"] = with_(*BASE) + ", n as (select count(*)::bigint as n from win) select method, model, n * t as token_evaluations, round(t / 128.0, 6) as ratio from n, (values ('attention', 128::bigint), ('segments', 512::bigint)) m(method, t), (select unnest(['small', 'large']) as model)"
