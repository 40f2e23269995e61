"""The experiments in a form that SQL can state, and the SQL.

Each experiment of plans.workloads runs once more under EXACT: code points (or bytes) as tokens, contexts of at most one of them, ranks as
dotted decimals or varints, sizes as stored, no times. Split, blocks, training, tuning, teaching, ranking, serializing and
reporting are the code of the full experiment. The SQL twin says the same from the tables alone: near copies by all pairs, counts and
ranks by windows, sizes by lengths of numbers.
"""

from __future__ import annotations

from . import workloads as w
from .relational import _HITS

QUERIES: dict = {}
SQL: dict[str, str] = {}

#: documents that have a text, with cluster_id (the smallest digest among near copies) and split.
SPLIT = """tx as (select distinct md5(text) k, text from documents where text is not null),
ws as (select k, regexp_extract_all(translate(text, 'ABCDEFGHIJKLMNOPQRSTUVWXYZ', 'abcdefghijklmnopqrstuvwxyz'), '[^\\x20\\x09-\\x0D]+') w from tx),
sh as (select distinct k, s from (select k, unnest(case when len(w) = 0 then [] when len(w) < 5 then [array_to_string(w, ' ')] else list_transform(range(1, len(w) - 3), lambda i: array_to_string(w[i:i + 4], ' ')) end) s from ws)),
sz as (select k, count(*) n from sh group by k),
lk as (
  select a, b from (select x.k a, y.k b, count(*) c from sh x join sh y on x.s = y.s and x.k < y.k group by all) p join sz m on m.k = a join sz n on n.k = b where c >= 0.8 * (m.n + n.n - c) - 1e-9
  union all select (select min(k) from ws where len(w) = 0), k from ws where len(w) = 0),
bi as (select a, b from lk where a <> b union select b, a from lk where a <> b),
re as (select a, b from bi union select r.a, l.b from re r join bi l on r.b = l.a),
cl as (select a k, least(a, min(b)) c from re group by a),
sc as (select d.*, coalesce(cl.c, md5(text)) cluster_id from documents d left join cl on cl.k = md5(text) where text is not null),
sp as (select *, case when h < 80 then 'train' when h < 90 then 'valid' else 'test' end split, ('0x' || substring(md5(cluster_id), 9, 6))::int % 100 part
  from (select *, ('0x' || substring(md5(cluster_id), 1, 6))::int % 100 h from sc))"""

#: The places of a text's symbols (a list of numbers) with the one before each, -1 at the start.
_CHAR = "list_transform(string_split({t}, ''), lambda x: unicode(x))"
_BYTE = "list_transform(regexp_extract_all(hex(encode({t})), '..'), lambda x: ('0x' || x)::int)"


def _symbols(source: str, keep: str, kind: str) -> str:
    return f"select {keep}, i - 1 pos, s[i] tok, case when i = 1 then -1 else s[i - 1] end before from (select {keep}, s, unnest(range(1, len(s) + 1)) i from (select {keep}, {kind.format(t='text')} s from ({source}) where text <> ''))"


def blocks(source: str, keep: str = "grp, doc_id") -> str:
    """(keep, block, text) of rows with a text."""
    return f"select {keep}, b block, substring(text, b * 10000 + 1, 10000) text from (select {keep}, text, unnest(range(greatest(1, ceil(len(text) / 10000.0)::bigint))) b from ({source}) where text is not null)"


def books(where: str, size: int, keep: str = "lang grp, book_no doc_id, 0 block, text") -> str:
    """The test texts of a language end to end, cut to books."""
    return f"select {keep} from (select lang, b::bigint book_no, substring(t, b * {size} + 1, {size}) text from (select lang, t, unnest(range(ceil(len(t) / {size}.0)::bigint)) b from (select lang, string_agg(text || chr(10), '' order by doc_id, text || chr(10)) t from sp where split = 'test' and {where} group by lang)))"


def evaluated(train: str, tests: str, models: dict[str, tuple[str, int]], kind: str = _CHAR, serializers=("dotted",), raw: bool = True, ids: str | None = None, vocab: int = 0x110000, soft: str | None = None, only: bool = False, name: str = "") -> str:
    """CTEs that end in ev, a row for each block, model and serializer.

    train: (model, weight, text); soft: further counts (model, before, tok, cnt); tests: blocks (grp, doc_id, block, text); models: the name in
    the report -> (model of train, length of context). ids: a model without prediction. only: models 'x:...' see only group x.
    """
    values = ", ".join(f"('{n}', '{src}', {order})" for n, (src, order) in models.items())
    more = f" union all select model, before, tok, cnt from ({soft})" if soft else ""
    fits = "and (strpos(k.name, ':') = 0 or split_part(k.name, ':', 1) = t.grp)" if only else ""
    length = {"dotted": "sum(len(rank::varchar)) + count(*) - 1", "varint": "sum(case when rank < 128 then 1 when rank < 16384 then 2 when rank < 2097152 then 3 else 4 end)"}
    sizes = " union all ".join(f"select name, grp, doc_id, block, '{s}' serializer, {length[s]} packed, count(*) n_tokens, avg(case when rank = 0 then 1.0 else 0 end) top1 from rt group by name, grp, doc_id, block" for s in serializers)
    raws = "union all select grp, doc_id, block, 'raw', '', 'raw', '', strlen(text), len(text), strlen(text), 0, null, null from bl where text <> ''" if raw else ""
    idq = f"union all select '{ids}', grp, doc_id, block, pos, tok from tk" if ids else ""
    return f"""tc as (select model, before, tok, sum(cnt) cnt from (select model, before, tok, weight cnt from ({_symbols(train, 'model, weight', kind)}){more}) group by all having sum(cnt) > 0),
g as (select model, tok, row_number() over (partition by model order by n desc, tok) - 1 g from (select model, tok, sum(cnt) n from tc group by all)),
gv as (select model, count(*) v from g group by model),
m as (select model, before, tok, row_number() over (partition by model, before order by cnt desc, tok) - 1 r from tc),
mk as (select * from (values {values}) x(name, src, ord)),
bl as ({tests}),
tk as ({_symbols('select grp, doc_id, block, text from bl', 'grp, doc_id, block', kind)}),
dt as (select distinct tok from tk),
pl as (select k.name, k.src, k.ord, t.tok, coalesce(g.g, coalesce(v.v, 0) + t.tok - (select count(*) from g u where u.model = k.src and u.tok < t.tok)) place from mk k cross join dt t left join gv v on v.model = k.src left join g on g.model = k.src and g.tok = t.tok),
dp as (select distinct before, tok from tk),
hi as (select p.name, p.src, p.ord, d.before, d.tok, p.place, m.r from dp d join pl p on p.tok = d.tok left join m on p.ord = 1 and m.model = p.src and m.before = d.before and m.tok = d.tok),
fx as (select h.name, h.before, h.tok, count(q.tok) more from hi h left join (m join g on g.model = m.model and g.tok = m.tok) q on q.model = h.src and q.before = h.before and q.g > h.place where h.r is null and h.ord = 1 group by all),
rk as (select h.name, h.before, h.tok, coalesce(h.r, h.place + coalesce(f.more, 0)) rank from hi h left join fx f on f.name = h.name and f.before = h.before and f.tok = h.tok),
rt as (select k.name, t.grp, t.doc_id, t.block, t.pos, k.rank from tk t join rk k on k.before = t.before and k.tok = t.tok {fits} {idq}),
hs as (select name, grp, doc_id, block, -sum(n / t * log2(n / t)) entropy from (select *, sum(n) over (partition by name, grp, doc_id, block) t from (select name, grp, doc_id, block, rank, count(*) n from rt group by all)) group by all),
ev as (
  select grp, doc_id, block, name model, serializer, 'raw' codec, 'individual' mode, strlen(text) raw_bytes, len(text) raw_chars, packed packed_bytes, n_tokens, top1, entropy rank_entropy
  from ({sizes}) z join hs using (name, grp, doc_id, block) join bl using (grp, doc_id, block)
  {raws})"""


def summary(keys: str, source: str = "ev") -> str:
    r = "raw_bytes / packed_bytes"
    return f"""select {keys}, count(*) n, round(sum(raw_bytes) / sum(packed_bytes), 6) ratio_bytes, round(sum(raw_chars) / sum(packed_bytes), 6) ratio_chars, round(8 * sum(packed_bytes) / sum(raw_chars), 6) bpc, round(8 * sum(packed_bytes) / sum(raw_bytes), 6) bpb,
  round(avg({r}), 6) ratio_mean, round(quantile_cont({r}, 0.5), 6) ratio_median, round(min({r}), 6) ratio_min, round(max({r}), 6) ratio_max, sum(n_tokens)::bigint n_tokens, round(avg(top1), 6) top1, round(avg(rank_entropy), 6) rank_entropy
  from {source} group by {keys}"""


KEYS = "grp, model, serializer, codec, mode"
_TEST = "select lang grp, doc_id, text from sp where split = 'test'"
_EN = "select source grp, doc_id, text from sp where split = 'test' and lang = 'en'"
_ALL = "select 'all' model, 1 weight, text from sp where split = 'train'"
_BASE = "select 'base' model, 1 weight, text from sp where split = 'train' and part < 25"
_LADDER = {"S": ("all", 0), "M": ("all", 1)}
_LATIN = "translate(text, 'abcdefghijklmnopqrstuvwxyzABCDEFGHIJKLMNOPQRSTUVWXYZ', '" + "".join(chr(0x0905 + i) for i in range(52)) + "')"
_FAR = f"select 'en shifted' grp, doc_id, {_LATIN} text from sp where split = 'test' and lang = 'en'"
_LINES = "select o_orderkey // 100 block, string_agg(line, chr(10) order by o_orderkey, line) text from (select o_orderkey, concat_ws(',', o_orderkey, o_custkey, o_orderstatus, o_orderpriority) line from orders) group by 1"


def gains(base: str, variants: dict[str, str]) -> str:
    values = ", ".join(f"('{n}', '{v}')" for n, v in variants.items())
    return f"""select grp, codec, variant, round(base, 6) ratio_base, round(ratio, 6) ratio_new, round(100 * (ratio / base - 1), 6) gain_pct from (
  select t.*, max(case when model = '{base}' then ratio end) over (partition by grp, serializer, codec) base from (select grp, model, serializer, codec, sum(raw_bytes) / sum(packed_bytes) ratio from ev group by all) t)
  join (values {values}) v(variant, model) using (model)"""


def _merged(name: str, own: str, weight: int = 4) -> str:
    """The base's texts and `weight` times the texts of the domain, under one name."""
    return f"select '{name}' model, 1 weight, text from sp where split = 'train' and part < 25 union all select '{name}', {weight}, text from ({own})"


def _taught(name: str, where: str) -> str:
    """Soft counts of a student of one symbol of context: the 32 likeliest followers under the teacher, trained on all, weigh 7 of 10 parts."""
    pairs = _symbols(f"select text from sp where {where}", "1 one", _CHAR)
    teach = _symbols("select text from sp where split = 'train'", "1 one", _CHAR)
    return f"""with te as (select before, tok, count(*) cnt from ({teach}) group by all),
  tl as (select * from (select *, row_number() over (partition by before order by cnt desc, tok) k, sum(cnt) over (partition by before order by cnt desc, tok rows between unbounded preceding and current row) upto from te) where k <= 32),
  tq as (select before, tok, cast(floor(700.0::double * cnt / max(upto) over (partition by before)) as bigint) q from tl),
  o0 as (select tok, cnt from (select tok, sum(cnt) cnt from te group by tok) order by cnt desc, tok limit 32),
  oq as (select tok, cast(floor(700.0::double * cnt / (select sum(cnt) from o0)) as bigint) q from o0),
  st as (select before, tok, count(*) n from ({pairs}) group by all),
  bn as (select before, sum(n) n from st group by before)
  select '{name}' model, before, tok, sum(c)::bigint cnt from (
    select before, tok, n * 300 c from st
    union all select b.before, q.tok, b.n * q.q from bn b join tq q on q.before = b.before
    union all select b.before, q.tok, b.n * q.q from bn b cross join oq q where b.before not in (select before from te)) group by all"""


def put(name: str, ctes: str, final: str) -> None:
    QUERIES[f"{name}_exact"] = lambda spark, d, f=w.QUERIES[name]: f(spark, d, w.EXACT)
    SQL[f"{name}_exact"] = f"with recursive {SPLIT}, {ctes} {final}"


def _fit(kind: str, name: str) -> str:
    ctes = evaluated(_ALL, blocks(_TEST), {"model": ("all", 1)}, kind, raw=False)
    h = "select grp, rank, count(*) n from rt group by all"
    share = lambda k: f"round(sum(case when rank < {k} then n else 0 end) / sum(n), 6) top{k}"
    return f"select * from (with {ctes} select grp, round(regr_slope(ln(n), rank), 6) slope, round(regr_r2(ln(n), rank), 6) r2, {share(1)}, {share(5)}, {share(10)}, round(sum(rank * n) / sum(n), 6) mean_rank, '{name}' tokenizer from ({h}) group by grp)"


put("w01_rank_distribution", "one as (select 1)", f"{_fit(_BYTE, 'byte')} union all {_fit(_CHAR, 'char')}")
put("w02_acceleration", evaluated(_ALL, blocks(_TEST), _LADDER, raw=False), "select name model, n_params, (select count(*) from bl where text <> '') n, (select sum(len(text)) from bl)::bigint chars, true same from (select 'S' name, count(*) n_params from g union all select 'M', (select count(*) from g) + (select count(*) from tc))")
_W3 = {"order0": ("all", 0), "model": ("all", 1)}
_GRP = "select case when lang = 'en' and source in ('src0', 'src1', 'src2', 'src3') then lang || '|' || source else lang end grp, doc_id, text from sp where split = 'test'"
put("w03_groups", evaluated(_ALL, blocks(_GRP), _W3, ids="ids"), summary(KEYS, "(select unnest(string_split(grp, '|')) grp, * exclude (grp) from ev)"))
_EIGHT = f"select * from ({books('true', 10_000)}) where doc_id < 8"
_MEAN = "select '{0}' mean_of, 'all' grp, model, serializer, codec, mode, null::bigint n, round({1}, 6) ratio from {2} group by model, serializer, codec, mode"
put(
    "w03_books", evaluated(_ALL, _EIGHT, _W3, ids="ids"),
    f"select 'group' mean_of, {KEYS}, count(*) n, round(sum(raw_bytes) / sum(packed_bytes), 6) ratio from ev group by {KEYS} union all "
    + _MEAN.format("macro", "avg(r)", f"(select {KEYS}, avg(raw_bytes / packed_bytes) r from ev group by {KEYS})") + " union all " + _MEAN.format("micro", "avg(raw_bytes / packed_bytes)", "ev") + " union all " + _MEAN.format("pooled", "sum(raw_bytes) / sum(packed_bytes)", "ev"),
)

_OWN = {x: f"select text from sp where split = 'train' and lang = '{x}'" for x in ("fr", "de")}
put("w04_fine_tuning", evaluated(" union all ".join([_BASE, *(_merged(f"tuned_{k}", v) for k, v in _OWN.items())]), blocks(_TEST), {m: (m, 1) for m in ("base", "tuned_fr", "tuned_de")}), gains("base", {f"tuned on {k}": f"tuned_{k}" for k in _OWN}))
_PLAIN = " union all ".join(f"select 'plain_{k}' model, 1 weight, text from ({v})" for k, v in _OWN.items())
_SOFT = " union all ".join(f"select * from ({_taught(f'taught_{k}', f'''split = 'train' and lang = '{k}' ''')})" for k in _OWN)
_W5 = ("base", "plain_fr", "plain_de", "taught_fr", "taught_de")
put("w05_distillation", evaluated(f"{_BASE} union all {_PLAIN}", blocks(_TEST), {m: (m, 1) for m in _W5}, soft=_SOFT), gains("base", {f"{a} on {k}": f"{a}_{k}" for a in ("taught", "plain") for k in _OWN}))
_STYLE = {"conversations": "select text from conversations where role = 'assistant' and text is not null", "orders": f"select text from ({_LINES})"}
put("w06_style_mismatch", evaluated(" union all ".join([_BASE, *(_merged(f"tuned_{k}", v) for k, v in _STYLE.items())]), blocks(_TEST + " and lang = 'en'"), {m: (m, 1) for m in ("base", "tuned_conversations", "tuned_orders")}), gains("base", {f"tuned on {k}": f"tuned_{k}" for k in _STYLE}))
_SRC = "select text from sp where split = 'train' and lang = 'en' and source = 'src0'"
put("w07_no_shift", evaluated(f"{_BASE} union all {_merged('tuned_src0', _SRC)}", blocks(_EN), {m: (m, 1) for m in ("base", "tuned_src0")}), gains("base", {"tuned on src0": "tuned_src0"}))

put("w08_model_sizes", evaluated(_ALL, blocks(_TEST), _LADDER), summary(KEYS))
put("w08_books", evaluated(_ALL, _EIGHT, _LADDER), summary(KEYS))
_SIZE = "select 'S' model, count(*) n_params, 16 + 8 + 12 * count(*) n_bytes from g union all select 'M', (select count(*) from g) + count(*), 24 + 12 * (select count(*) from g) + 16 * count(distinct before) + 8 + 12 * count(*) from tc"
put("w08_amortised", evaluated(_ALL, blocks(_TEST), _LADDER, raw=False), f"select model, codec, round(raw / packed, 6) ratio_bytes, n_params, n_bytes, round(raw / (packed + n_bytes), 6) ratio_with_model from (select model, codec, sum(raw_bytes) raw, sum(packed_bytes) packed from ev group by all) join ({_SIZE}) using (model)")
put("w08_monotonicity", evaluated(_ALL, blocks(_TEST), _LADDER, raw=False), "select s.grp, 1::bigint steps, (m.r < s.r)::bigint violations, 'ratio' measure from (select grp, sum(raw_bytes) / sum(packed_bytes) r from ev where model = 'S' group by grp) s join (select grp, sum(raw_bytes) / sum(packed_bytes) r from ev where model = 'M' group by grp) m using (grp)")
_LONGEST = "select lang grp, doc_id, text from sp where split = 'test' and doc_id in (select arg_max(doc_id, (n_chars, doc_id)) from sp where split = 'test' group by lang)"
put(
    "w09_per_file", evaluated(_ALL, blocks(_LONGEST), _LADDER),
    "select grp, codec, round(max(ratio) filter (model <> 'raw'), 6) best_ratio, arg_max(model, (ratio, model)) filter (model <> 'raw') best_model, round(min(bpc) filter (model <> 'raw'), 6) best_bpc, max(tokens) filter (model <> 'raw') n_tokens, "
    "round(arg_max(entropy, (ratio, model)) filter (model <> 'raw'), 6) rank_entropy, round(max(ratio) filter (model = 'raw'), 6) raw_ratio from (select grp, model, codec, sum(raw_bytes) / sum(packed_bytes) ratio, 8 * sum(packed_bytes) / sum(raw_chars) bpc, sum(n_tokens)::bigint tokens, avg(rank_entropy) entropy from ev group by all) group by grp, codec",
)
put("w10_codecs_on_a_book", evaluated(_ALL, books("lang = 'en'", 100_000), {"M": ("all", 1)}), summary(KEYS))
_GAIN = "select grp, model, sum(raw_bytes) filter (serializer = 'dotted') / sum(packed_bytes) filter (serializer = 'dotted') a, sum(raw_bytes) filter (serializer = 'dotted') / sum(packed_bytes) filter (serializer = 'varint') b from ev group by all"
put("w10_codec_gain", evaluated(_ALL, blocks(_TEST), _LADDER, serializers=("dotted", "varint"), raw=False), f"select grp, model, round(a, 6) ratio_first, round(b, 6) ratio_second, round(100 * (b / a - 1), 6) gain_pct from ({_GAIN})")
_LEAK = f"select * from ({_taught('student', '''lang = 'en' and split = 'train' ''')}) union all select * from ({_taught('student_leak', '''lang = 'en' and split in ('train', 'test')''')})"
put("w11_seen_in_part", evaluated(f"{_BASE} union all {_ALL}", books("lang = 'en'", 28_851), {"base": ("base", 1), "teacher": ("all", 1), "student": ("student", 1), "student_leak": ("student_leak", 1)}, soft=_LEAK), summary(KEYS))

_ENGLISH = "select 'english' model, 1 weight, text from sp where split = 'train' and lang = 'en'"
_PIECES = books("true", 100_000)
_FAR_PIECES = f"select 'en shifted' grp, doc_id, block, {_LATIN} text from ({_PIECES}) where grp = 'en'"
put("w12_foreign_languages", evaluated(_ENGLISH, f"{blocks(_TEST)} union all {blocks(_FAR)}", {"english": ("english", 1)}), summary(KEYS))
put("w12_long", evaluated(_ENGLISH, f"{_PIECES} union all {_FAR_PIECES}", {"english": ("english", 1)}), summary(KEYS))
_EACH = f"{_ENGLISH} union all select lang, 1, text from sp where split = 'train' union all select 'en shifted', 1, {_LATIN} from sp where split = 'train' and lang = 'en'"
_OWNS = {"english": ("english", 1)} | {f"{x}:own": (x, 1) for x in ("de", "en", "es", "fr", "en shifted")}
put("w13_language_models", evaluated(_EACH, f"{blocks(_TEST)} union all {blocks(_FAR)}", _OWNS, only=True), summary(KEYS))
put("w13_long", evaluated(_EACH, f"{_PIECES} union all {_FAR_PIECES}", _OWNS, only=True), summary(KEYS))

_TABLES = "select 'documents' grp, doc_id, text from documents union all select 'pages', page_id, html from pages union all select 'conversations', conv_id, text from conversations"
QUERIES["w14_baselines_exact"] = lambda spark, d: w.w14_baselines(spark, d, w.EXACT)
SQL["w14_baselines_exact"] = f"with ev as (select grp, 'raw' codec, strlen(text) raw_bytes, len(text) raw_chars, strlen(text) packed_bytes, 0 n_tokens, null::double top1, null::double rank_entropy from ({blocks(_TABLES)}) where text <> '') {summary('grp, codec')}"
put("w15_second_stage", evaluated(_ALL, blocks(_TEST), {"model": ("all", 1)}, serializers=("dotted", "varint")), summary(KEYS, "(select 'all' grp, * exclude (grp) from ev)"))
_TOK = lambda kind, name: f"select * from (with {evaluated(_ALL, blocks(_TEST), {f'{name} ranks': ('all', 1)}, kind, ('dotted', 'varint'), False, f'{name} ids')} {summary(KEYS, '''(select 'all' grp, * exclude (grp) from ev)''')})"
put("w15_tokenizers", "one as (select 1)", f"{_TOK(_BYTE, 'byte')} union all {_TOK(_CHAR, 'char')}")
_CHAIN = """nx as (select before, tok from m where r = 0), top as (select tok from g where g = 0),
ch as (select s.tok root, 0 j, s.tok here from (select distinct before tok from tk) s union all select c.root, c.j + 1, coalesce(n.tok, (select tok from top)) from ch c left join nx n on n.before = c.here where c.j < 15),
ba as (select 'batch' || k mode, k, t.grp, t.doc_id, t.block, t.pos, t.tok, ch.here before from (values (1), (2), (4), (8), (16)) x(k) cross join tk t join tk f on f.grp = t.grp and f.doc_id = t.doc_id and f.block = t.block and f.pos = t.pos - t.pos % k join ch on ch.root = f.before and ch.j = t.pos % k),
bd as (select distinct before, tok from ba),
bh as (select b.before, b.tok, p.place, m.r from bd b join pl p on p.tok = b.tok left join m on m.before = b.before and m.tok = b.tok),
bf as (select h.before, h.tok, count(q.tok) more from bh h left join (m join g on g.model = m.model and g.tok = m.tok) q on q.before = h.before and q.g > h.place where h.r is null group by all),
br as (select h.before, h.tok, coalesce(h.r, h.place + coalesce(f.more, 0)) rank from bh h left join bf f on f.before = h.before and f.tok = h.tok),
bt as (select b.mode, b.k, b.grp, b.doc_id, b.block, r.rank from ba b join br r on r.before = b.before and r.tok = b.tok),
be as (select mode, grp, doc_id, block, -sum(n / t * log2(n / t)) entropy from (select *, sum(n) over (partition by mode, grp, doc_id, block) t from (select mode, grp, doc_id, block, rank, count(*) n from bt group by all)) group by all),
al as (select 'all' grp, model, serializer, codec, mode, 1 k, raw_bytes, raw_chars, packed_bytes, n_tokens, top1, rank_entropy from ev
  union all select 'all', 'model', 'dotted', 'raw', mode, k, strlen(text), len(text), packed, n, top1, entropy from (select mode, k, grp, doc_id, block, sum(len(rank::varchar)) + count(*) - 1 packed, count(*) n, avg(case when rank = 0 then 1.0 else 0 end) top1 from bt group by all) z join be using (mode, grp, doc_id, block) join bl using (grp, doc_id, block))"""
put("w16_batch_inference", evaluated(_ALL, blocks(_TEST), {"model": ("all", 1)}, raw=False) + ", " + _CHAIN, f"select * from ({summary(KEYS, 'al')}) join (select mode, sum(ceil(n_tokens / k))::bigint calls from al group by mode) using (mode)")
put("w17_context_size", evaluated(_ALL, blocks(_TEST), {"static0": ("all", 0), "static1": ("all", 1)}), summary(KEYS, "(select 'all' grp, * exclude (grp) from ev)"))

_CORR = ", ".join(f"round(corr(raw_bytes / packed_bytes, {x}), 6) {n}" for n, x in (("with_top1", "top1"), ("with_entropy", "rank_entropy")))
put("w18_factors", evaluated(_ALL, blocks(_TEST), {"model": ("all", 1)}, raw=False), f"select quality, codec, {_CORR}, count(*) n from ev left join (select doc_id, min(quality) quality from labels group by doc_id) using (doc_id) group by quality, codec")
_LENGTHS = " union all ".join(f"select '{n}' grp, doc_id, block, text from ({books('''lang = 'en' ''', n)}) where len(text) = {n}" for n in (1_000, 3_000, 10_000, 30_000, 100_000))
put("w19_input_length", evaluated(_ALL, _LENGTHS, {"model": ("all", 1)}), summary(KEYS))
_PROPS = "select event_id // 500 doc_id, string_agg(props, chr(10) order by props) text from events group by 1"
put("w20_not_prose", evaluated(_ALL, blocks(f"select 'html' grp, page_id doc_id, html text from pages union all select 'order lines', block, text from ({_LINES}) union all select 'json', doc_id, text from ({_PROPS})"), {"prose model": ("all", 1)}), summary(KEYS))
_HIT = f"ht as ({_HITS})"
_CLEAN = "select text from sp where split = 'train' and doc_id not in (select doc_id from ht)"
_MIXED = "select case when doc_id in (select doc_id from ht) then 'leaked' else 'clean' end grp, doc_id, text from sp where split = 'test' or doc_id in (select doc_id from ht)"
put("w21_contamination", _HIT + ", " + evaluated(f"select 'without' model, 1 weight, text from ({_CLEAN}) union all select 'with', 1, text from ({_CLEAN}) union all select 'with', 1, text from benchmark where text is not null", blocks(_MIXED), {m: (m, 1) for m in ("without", "with")}), summary(KEYS))
_FR = "select text from sp where split = 'train' and lang = 'fr'"
put(
    "checkpoint_selection", evaluated(" union all ".join(_merged(f"w{k}", _FR, k) for k in (0, 1, 4, 16)), blocks("select split grp, doc_id, text from sp where split in ('valid', 'test') and lang = 'fr'"), {f"w{k}": (f"w{k}", 1) for k in (0, 1, 4, 16)}, raw=False),
    "select model, round(v, 6) \"valid\", round(t, 6) test, v = max(v) over () chosen from (select model, sum(raw_bytes) filter (grp = 'valid') / sum(packed_bytes) filter (grp = 'valid') v, sum(raw_bytes) filter (grp = 'test') / sum(packed_bytes) filter (grp = 'test') t from ev group by model)",
)


def relational_ranks(spark, d):
    """Ranks of the test side under a model of all training texts, by joins alone."""
    from ..operators import ranks, training

    tok = w.EXACT.tok
    counts = training.counts(w.documents(spark, d).where("split = 'train'"), tok, 1)
    return ranks.histogram(w.side(spark, d, "test"), counts, tok, 1)


def delta_counts(spark, d):
    """The sparse table that tuning on French adds to a base, four times its counts."""
    from ..operators import training

    own = training.counts(w.documents(spark, d).where("split = 'train' and lang = 'fr'"), w.EXACT.tok, 1, domain="lang")
    return training.delta(own, 4)


_FRENCH = _symbols("select text from sp where split = 'train' and lang = 'fr'", "1 one", _CHAR)
QUERIES["delta_counts"] = delta_counts
SQL["delta_counts"] = f"with recursive {SPLIT}, t as ({_FRENCH}) select 'fr' domain, level, ctx, tok token, 4 * count(*) more from (select 0 level, 0::bigint ctx, tok from t union all select 1, (before + 1)::bigint, tok from t) group by all"
QUERIES["relational_ranks"] = relational_ranks
SQL["relational_ranks"] = f"with recursive {SPLIT}, {evaluated(_ALL, blocks(_TEST), {'model': ('all', 1)}, raw=False)} select grp, rank, count(*) n from rt group by all"
w.SQL["split_by_cluster"] = f"with recursive {SPLIT} select a.doc_id, s.cluster_id, s.split, count(*) n from ({w._AGAIN}) a join (select distinct text, cluster_id, split from sp) s on s.text = a.text group by all"
