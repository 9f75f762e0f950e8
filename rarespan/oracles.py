"""DuckDB SQL that states, independently of the Spark plans, what the registered queries return."""

from __future__ import annotations

from rarespan.functions.breakpoints import LETTERS, cuts, summary_breaks

_CENTS = "cast(round({c} * 100) as bigint)"
_UNITS = "cast(round({c}) as bigint)"


def _dense(rows: str) -> str:
    """Series with gaps filled by zero, from a query with series_id, step, x."""
    return f"""
    r as ({rows}), b as (select series_id, min(step) as lo, max(step) as hi from r group by 1),
    g as (select series_id, lo, unnest(generate_series(lo, hi)) as step from b),
    s as (select g.series_id, cast(g.step - g.lo + 1 as bigint) as pos, cast(coalesce(r.x, 0) as bigint) as x
          from g left join r on r.series_id = g.series_id and r.step = g.step)"""


def _epoch(c: str, step: int) -> str:
    return f"cast(epoch_us({c}) // {step * 1_000_000} as bigint)"


def _nation(of: str) -> str:
    month = "cast(year(o_orderdate) * 12 + month(o_orderdate) as bigint)"
    name = "r_name || '/' || n_name"
    where = "join nation on {k} = n_nationkey join region on n_regionkey = r_regionkey"
    if of == "customer":
        return f"select {name} as series_id, {month} as step, sum({_UNITS.format(c='o_totalprice')}) as x from orders join customer on o_custkey = c_custkey {where.format(k='c_nationkey')} group by 1, 2"
    return f"select {name} as series_id, {month} as step, sum({_UNITS.format(c='l_extendedprice')}) as x from lineitem join orders on l_orderkey = o_orderkey join supplier on l_suppkey = s_suppkey {where.format(k='s_nationkey')} group by 1, 2"


#: Series by name: the body of a WITH clause that ends in a table s (series_id, pos, x).
SERIES = {
    "events_hour": _dense(f"select 'all' as series_id, {_epoch('ts', 3600)} as step, sum({_CENTS.format(c='value')}) as x from events group by 1, 2"),
    "events_type_hour": _dense(f"select event_type as series_id, {_epoch('ts', 3600)} as step, sum({_CENTS.format(c='value')}) as x from events group by 1, 2"),
    "events_seq": f"s as (select 'all' as series_id, row_number() over (order by ts, event_id) as pos, {_CENTS.format(c='value')} as x from events)",
    "events_user": f"s as (select cast(user_id as varchar) as series_id, row_number() over (partition by user_id order by ts, event_id) as pos, {_CENTS.format(c='value')} as x from events)",
    "orders_day": _dense(f"select 'all' as series_id, {_epoch('o_orderdate', 86400)} as step, sum({_UNITS.format(c='o_totalprice')}) as x from orders group by 1, 2"),
    "orders_walk": f"""m as (select cast(floor(avg({_CENTS.format(c='o_totalprice')})) as bigint) as m from orders),
    t as (select row_number() over (order by o_orderkey) as pos, {_CENTS.format(c='o_totalprice')} - m as d from orders, m),
    s as (select 'walk' as series_id, pos, cast(sum(case when d < 0 then -((-d) // 1000000) else d // 1000000 end) over (order by pos) as bigint) as x from t)""",
    "lineitem_seq": f"s as (select 'lineitem' as series_id, row_number() over (order by l_orderkey, l_linenumber, l_partkey, l_suppkey, l_shipdate) as pos, {_UNITS.format(c='l_extendedprice')} as x from lineitem)",
    "lineitem_day": _dense(f"select l_returnflag as series_id, {_epoch('l_shipdate', 86400)} as step, sum({_UNITS.format(c='l_quantity')}) as x from lineitem group by 1, 2"),
    "nation_month": _dense(_nation("customer")),
    "supplier_month": _dense(_nation("supplier")),
    "part_cycle": """p0 as (select p_partkey // 80 as block, row_number() over (partition by p_partkey // 80 order by p_partkey) - 1 as i, cast(p_size as bigint) as x, count(*) over (partition by p_partkey // 80) as n from part),
    p as (select block, i, x from p0 where n = 80),
    s as (select 'cycle-' || block as series_id, cast(rep * 40 + i % 40 + 1 as bigint) as pos, x from p, (select unnest(generate_series(0, 29)) as rep) r where (rep <> 17 and i < 40) or (rep = 17 and i >= 40))""",
    "doc_lengths": "s as (select lang as series_id, row_number() over (partition by lang order by doc_id) as pos, n_chars as x from documents)",
}

#: Token tables by name: a WITH body that ends in t (series_id, pos, word).
TOKENS = {
    "doc_words": r"t as (select series_id, cast(p as bigint) as pos, words[p] as word from (select cast(doc_id as varchar) as series_id, string_split_regex(trim(text), '\s+') as words from documents) q, lateral (select unnest(generate_series(1, len(words))) as p))",
    "page_tags": r"t as (select series_id, cast(p as bigint) as pos, lower(tags[p]) as word from (select cast(page_id as varchar) as series_id, regexp_extract_all(html, '</?([a-zA-Z][a-zA-Z0-9]*)') as tags from pages) q, lateral (select unnest(generate_series(1, len(tags))) as p))",
    "conv_roles": "t as (select cast(conv_id as varchar) as series_id, row_number() over (partition by conv_id order by turn) as pos, role as word from conversations)",
}


def series(name: str) -> str:
    return f"with {SERIES[name]} select series_id, pos, x from s"


def tokens(name: str) -> str:
    return f"with {TOKENS[name]} select series_id, pos, word from t"


_O = "partition by series_id order by pos"


def coefficients(n: int, w: int, floor: bool = False) -> str:
    """Select list entries c0 .. c{w-1} over a table with t1, v and s0 ..; each from its own frame over raw values."""
    return ", ".join(f"case when v <= 0 then 0.0e0 else cast(s{i} - t1 as double) / sqrt(cast(v as double) * {n / (n - 1)!r}) end as c{i}" for i in range(w))


def windows(n: int, w: int) -> str:
    """CTEs m (sums) and q (coefficients) over s."""
    parts = []
    for i in range(w):
        (lo, a), (hi, b) = divmod(i * n, w), divmod((i + 1) * n, w)
        total = f"{w} * coalesce(sum(x) over ({_O} rows between {lo} following and {hi - 1} following), 0)" if hi > lo else "0"
        total += f" - {a} * lead(x, {lo}) over ({_O})" if a else ""
        total += f" + {b} * lead(x, {hi}) over ({_O})" if b else ""
        parts.append(f"cast({total} as bigint) as s{i}")
    frame = f"over ({_O} rows between current row and {n - 1} following)"
    return f"""m as (select series_id, pos, cast(sum(x) {frame} as bigint) as t1, cast({n} * sum(x * x) {frame} - sum(x) {frame} * sum(x) {frame} as bigint) as v,
        count(*) {frame} as len, {', '.join(parts)} from s),
    q as (select series_id, pos, {coefficients(n, w)} from m where len = {n})"""


def letter(c: str, a: int) -> str:
    count = " + ".join(f"(case when {c} >= {x!r}e0 then 1 else 0 end)" for x in cuts(a))
    return f"substr('{LETTERS}', 1 + {count}, 1)"


def word(w: int, a: int) -> str:
    return " || ".join(letter(f"c{i}", a) for i in range(w))


def words_cte(n: int, w: int, a: int) -> str:
    return f"{windows(n, w)}, t as (select series_id, pos, {word(w, a)} as word from q)"


def words(name: str, n: int, w: int, a: int) -> str:
    return f"with {SERIES[name]}, {words_cte(n, w, a)} select series_id, pos, word from t"


def paa(name: str, n: int, w: int) -> str:
    return f"with {SERIES[name]}, {windows(n, w)} select series_id, pos, " + ", ".join(f"round(c{i}, 9) as c{i}" for i in range(w)) + " from q"


_RUNS = f"k as (select series_id, pos, word, lead(pos) over ({_O}) as nxt from (select *, lag(word) over ({_O}) as b from t) z where b is null or b <> word)"


def collapsed(name: str, n: int, w: int, a: int) -> str:
    return f"""with {SERIES[name]}, {words_cte(n, w, a)}, {_RUNS}, e as (select series_id, max(pos) as last_pos from s group by 1)
    select series_id, {w} as w, {a} as a, pos, word, cast(row_number() over ({_O}) - 1 as bigint) as tok_ix, coalesce(nxt - 1, last_pos) as run_end from k join e using (series_id)"""


def tokens_of(name: str, n: int, pairs: list[tuple[int, int]]) -> str:
    """Collapsed tokens (series_id, w, a, tok_ix, word) for several resolutions."""
    return " union all ".join(f"select series_id, w, a, tok_ix, word from ({collapsed(name, n, w, a)}) z" for w, a in pairs)


def expanded(name: str, n: int, w: int, a: int) -> str:
    return f"""with {SERIES[name]}, {words_cte(n, w, a)}, e as (select series_id, max(pos) as last_pos from s group by 1),
    z as (select s.series_id, s.pos, last_value(t.word ignore nulls) over (partition by s.series_id order by s.pos) as word from s left join t on t.series_id = s.series_id and t.pos = s.pos)
    select series_id, pos, word from z where word is not null"""


def frequencies_cte(name: str, n: int, pairs: list[tuple[int, int]]) -> str:
    """d (series_id, w, a, pos, d): at each window, how many windows of its series have the same word."""
    each = " union all ".join(
        f"select series_id, {w} as w, {a} as a, pos, count(*) over (partition by series_id, word) as d from (with {SERIES[name]}, {words_cte(n, w, a)} select * from t) z{i}" for i, (w, a) in enumerate(pairs)
    )
    return f"d as ({each})"


_STATS = """st as (select series_id, w, a, count(*) as len, cast(sum(d) as bigint) as total, cast(max(d) as bigint) as top,
    cast(cast(count(*) as hugeint) * sum(d * d) - cast(sum(d) as hugeint) * sum(d) as double) as spread from d group by 1, 2, 3)"""


def curve_stats(name: str, n: int, pairs) -> str:
    return f"with {frequencies_cte(name, n, pairs)}, {_STATS} select series_id, w, a, len, total, top, spread, round(sqrt(spread) / len, 9) as sd, round(cast(total as double) / len, 9) as level from st"


def _kept(tau: float) -> str:
    return f"""kp as (select *, cast(row_number() over (partition by series_id order by spread desc, w, a) as int) as rank,
        greatest(1, ceil({tau}e0 * count(*) over (partition by series_id) - 1e-9)) as most from st), kk as (select * from kp where rank <= most)"""


def keep(name: str, n: int, pairs, tau: float) -> str:
    return f"with {frequencies_cte(name, n, pairs)}, {_STATS}, {_kept(tau)} select series_id, w, a, spread, rank from kk"


def scale(name: str, n: int, pairs, tau: float, norm: str = "max") -> str:
    v = {"max": "case when top > 0 then cast(d as double) / top else 0 end", "none": "cast(d as double)", "minmax": "case when top > low then cast(d - low as double) / (top - low) else 0 end"}[norm]
    return f"""with {frequencies_cte(name, n, pairs)}, {_STATS}, {_kept(tau)}, lo as (select series_id, w, a, min(d) as low from d group by 1, 2, 3)
    select series_id, w, a, pos, round({v}, 9) as v from d join kk using (series_id, w, a) join lo using (series_id, w, a)"""


def combine_cte(name: str, n: int, pairs, tau: float, how: str = "median") -> str:
    f = {"median": "median", "mean": "avg", "min": "min", "max": "max"}[how]
    return f"""{frequencies_cte(name, n, pairs)}, {_STATS}, {_kept(tau)},
    cu as (select series_id, pos, {f}(cast(d as double) / top) as de from d join kk using (series_id, w, a) group by 1, 2)"""


def combine(name: str, n: int, pairs, tau: float, how: str = "median") -> str:
    return f"with {combine_cte(name, n, pairs, tau, how)} select series_id, pos, round(de, 9) as de from cu"


def plateaus(name: str, n: int, pairs, tau: float) -> str:
    return f"""with {combine_cte(name, n, pairs, tau)},
    c0 as (select series_id, pos, round(de, 9) as de from cu),
    a as (select *, lag(de) over ({_O}) as b, max(pos) over (partition by series_id) as last from c0),
    r as (select series_id, pos as lo, de, last from a where b is null or b <> de),
    z as (select *, coalesce(lead(lo) over (partition by series_id order by lo) - 1, last) as hi, lag(de) over (partition by series_id order by lo) as l, lead(de) over (partition by series_id order by lo) as r from r)
    select series_id, cast(row_number() over (partition by series_id order by de, lo) as int) as rank, lo, hi, lo as loc, de as value from z
    where (l is null or de < l) and (r is null or de < r) and not (l is null and r is null)"""


def top_windows(name: str, n: int, pairs, tau: float, k: int = 3) -> str:
    steps, prev = [], "v"
    for r in range(1, k + 1):
        steps.append(f"m{r} as (select series_id, min(value) as value, arg_min(pos, row(value, pos)) as loc from {prev} group by 1)")
        steps.append(f"v{r} as (select p.* from {prev} p join m{r} using (series_id) where abs(p.pos - loc) >= {n})")
        prev = f"v{r}"
    steps = [s.replace(" p.* ", " p.series_id, p.pos, p.value ") for s in steps]
    out = " union all ".join(f"select series_id, cast({r} as int) as rank, loc as lo, loc + {n - 1} as hi, loc, value from m{r}" for r in range(1, k + 1))
    return f"""with {combine_cte(name, n, pairs, tau)}, c0 as (select series_id, pos, round(de, 6) as de from cu),
    v0 as (select series_id, pos, round(sum(de) over ({_O} rows between current row and {n - 1} following), 6) as value, count(*) over ({_O} rows between current row and {n - 1} following) as len from c0),
    v as (select series_id, pos, value from v0 where len = {n}), {', '.join(steps)} {out}"""


def discord(name: str, n: int, where: str = "true") -> str:
    """Nearest-neighbour distance of each window, from all pairs."""
    return f"""with {SERIES[name]}, u as (select * from s where {where}),
    f as (select series_id, pos, list(x) over (partition by series_id order by pos rows between current row and {n - 1} following) as xs from u),
    wn as (select series_id, pos, xs, list_avg(xs) as mu, list_stddev_pop(xs) as sd from f where len(xs) = {n}),
    z as (select series_id, pos, case when sd = 0 then list_transform(xs, lambda x: 0.0e0) else list_transform(xs, lambda x: (x - mu) / sd) end as z from wn)
    select a.series_id, a.pos, round(sqrt(min(list_sum(list_transform(list_zip(a.z, b.z), lambda p: (p[1] - p[2]) * (p[1] - p[2]))))), 6) as distance
    from z a join z b on a.series_id = b.series_id and abs(a.pos - b.pos) >= {n} group by 1, 2"""


def summary_breaks_sql(a_max: int) -> str:
    rows = ", ".join(f"({i + 1}, round({x!r}e0, 12))" for i, x in enumerate(summary_breaks(a_max)))
    return f"select cast(ix as int) as ix, cut from (values {rows}) v(ix, cut)"


def symbol_matrix_sql(a_max: int) -> str:
    """From the definition: an interval's letter is the number of an alphabet's cuts at or below the interval's lower end."""
    breaks = summary_breaks(a_max)
    iv = ", ".join(["(0, -1e300)", *(f"({i + 1}, {x!r}e0)" for i, x in enumerate(breaks))])
    al = ", ".join(f"({a}, {x!r}e0)" for a in range(2, a_max + 1) for x in cuts(a))
    return f"""with iv(ix, low) as (values {iv}), al(a, cut) as (values {al})
    select cast(ix as int) as ix, cast(a as int) as a, substr('{LETTERS}', 1 + cast(sum(case when cut <= low + 1e-12 then 1 else 0 end) as int), 1) as letter from iv, al group by ix, a"""




def rounds_cte(name: str, n: int, w: int, a: int, rounds: int) -> str:
    """CTEs of the rounds inducer over the collapsed words: q{r} the sequence before round r, t{r} with the pairs to replace marked."""
    steps = [f"q0 as materialized (select series_id, tok_ix, word as sym, cast(1 as bigint) as len, pos, run_end from ({collapsed(name, n, w, a)}) z0)"]
    over = "partition by series_id order by tok_ix"
    for r in range(rounds):
        if r % 2 == 0:
            cand = "(rn - max(case when ch then rn end) over (partition by series_id order by tok_ix)) % 2 = 0 and nxt = sym"
        else:
            left = f"substr(md5('{r}:' || sym), 1, 1) < '8'"
            right = f"substr(md5('{r}:' || nxt), 1, 1) >= '8'"
            cand = f"nxt <> sym and {left} and {right}"
        steps.append(f"a{r} as (select *, lead(sym) over ({over}) as nxt, lead(len) over ({over}) as nlen, row_number() over ({over}) as rn, lag(sym) over ({over}) is distinct from sym as ch from q{r})")
        steps.append(f"b{r} as (select *, coalesce({cand}, false) as cand from a{r})")
        steps.append(f"c{r} as (select *, cand and count(*) over (partition by series_id, sym, nxt, cand) >= 2 as rep from b{r})")
        steps.append(f"t{r} as materialized (select *, 'N' || md5(sym || '|' || nxt) as name, coalesce(lag(rep) over ({over}), false) as gone from c{r})")
        steps.append(f"q{r + 1} as materialized (select series_id, tok_ix, case when rep then name else sym end as sym, len + case when rep then nlen else 0 end as len, pos, run_end from t{r} where not gone)")
    return ", ".join(steps)


def rounds_sequence(name: str, n: int, w: int, a: int, rounds: int) -> str:
    return f"with {rounds_cte(name, n, w, a, rounds)} select series_id, {w} as w, {a} as a, tok_ix, sym, len from q{rounds}"


def rounds_density(name: str, n: int, w: int, a: int, rounds: int) -> str:
    """Points covered at each depth, from the rule instances of the rounds inducer."""
    return f"""with {rounds_density_cte(name, n, w, a, rounds)}
    select series_id, cast(d as bigint) as d, count(*) as points from dp group by 1, 2"""


def rounds_density_cte(name: str, n: int, w: int, a: int, rounds: int) -> str:
    """dp (series_id, pos, d): at each position, how many instances of rules used at least twice cover it."""
    rules = " union ".join(f"select series_id, name, sym as x, nxt as y from t{r} where rep" for r in range(rounds))
    spans = " union all ".join(f"select series_id, name, tok_ix as lo_tok, tok_ix + len + nlen - 1 as hi_tok from t{r} where rep" for r in range(rounds))
    return f"""{rounds_cte(name, n, w, a, rounds)}, ru as materialized ({rules}), sp as materialized ({spans}),
    us as (select series_id, name, count(*) as uses from (select series_id, x as name from ru union all select series_id, y from ru union all select series_id, sym from q{rounds}) z group by 1, 2),
    ok as materialized (select sp.* from sp join us using (series_id, name) where uses >= 2),
    pl as materialized (select ok.series_id, l.pos as lo, h.run_end as hi from ok join q0 l on l.series_id = ok.series_id and l.tok_ix = lo_tok join q0 h on h.series_id = ok.series_id and h.tok_ix = hi_tok),
    en as (select series_id, max(run_end) as last_pos from q0 group by 1),
    gr as (select series_id, unnest(generate_series(1, last_pos)) as pos from en),
    dp as (select gr.series_id, gr.pos, count(pl.lo) as d from gr left join pl on pl.series_id = gr.series_id and gr.pos between pl.lo and pl.hi group by 1, 2)"""


def rounds_single(name: str, n: int, w: int, a: int, rounds: int, k: int = 3) -> str:
    """A whole single run: words, rounds grammar, density, and the k windows of smallest summed density."""
    steps, prev = [], "v"
    for r in range(1, k + 1):
        steps.append(f"m{r} as (select series_id, min(value) as value, arg_min(pos, row(value, pos)) as loc from {prev} group by 1)")
        steps.append(f"v{r} as (select p.series_id, p.pos, p.value from {prev} p join m{r} using (series_id) where abs(p.pos - loc) >= {n})")
        prev = f"v{r}"
    out = " union all ".join(f"select series_id, cast({r} as int) as rank, loc as lo, loc + {n - 1} as hi, loc, value from m{r}" for r in range(1, k + 1))
    return f"""with {rounds_density_cte(name, n, w, a, rounds)},
    v0 as (select series_id, pos, cast(sum(d) over ({_O} rows between current row and {n - 1} following) as double) as value, count(*) over ({_O} rows between current row and {n - 1} following) as len from dp),
    v as materialized (select series_id, pos, value from v0 where len = {n}), {', '.join(steps)} {out}"""


def committee_by_rounds(name: str, n: int, pairs: list[tuple[int, int]], rounds: int, tau: float, k: int = 3) -> str:
    """The whole committee: words, rounds grammars, densities, spread, scaling, median, and the windows of smallest sum."""
    each = " union all ".join(f"select series_id, {w} as w, {a} as a, pos, d from (with {rounds_density_cte(name, n, w, a, rounds)} select * from dp) y{i}" for i, (w, a) in enumerate(pairs))
    steps, prev = [], "v"
    for r in range(1, k + 1):
        steps.append(f"m{r} as (select series_id, min(value) as value, arg_min(pos, row(value, pos)) as loc from {prev} group by 1)")
        steps.append(f"v{r} as (select p.series_id, p.pos, p.value from {prev} p join m{r} using (series_id) where abs(p.pos - loc) >= {n})")
        prev = f"v{r}"
    out = " union all ".join(f"select series_id, cast({r} as int) as rank, loc as lo, loc + {n - 1} as hi, loc, value from m{r}" for r in range(1, k + 1))
    return f"""with d as materialized ({each}), {_STATS}, {_kept(tau)},
    cu as (select series_id, pos, median(case when top > 0 then cast(d as double) / top else 0 end) as de from d join kk using (series_id, w, a) group by 1, 2),
    c0 as (select series_id, pos, round(de, 6) as de from cu),
    v0 as (select series_id, pos, round(sum(de) over ({_O} rows between current row and {n - 1} following), 6) as value, count(*) over ({_O} rows between current row and {n - 1} following) as len from c0),
    v as materialized (select series_id, pos, value from v0 where len = {n}), {', '.join(steps)} {out}"""


def planted_truth(labels: int, copies: int, normal: int = 20, length: int = 64, seed: int = 7) -> str:
    """Where the one foreign instance of each planted series begins: instances drawn and placed by md5 numbers."""
    return f"""with e as (select vec_id, label from embeddings), c as (select unnest(generate_series(0, {copies - 1})) as copy), d as (select unnest(generate_series(0, {labels - 1})) as dataset),
    r as (select dataset, copy, vec_id, label = dataset as own, row_number() over (partition by dataset, copy, label = dataset order by md5('{seed}:' || dataset || ':' || copy || ':' || vec_id), vec_id) - 1 as rank from e, c, d),
    t as (select dataset, copy, count(*) as have from r where own and rank < {normal} group by 1, 2),
    b as (select t.dataset, t.copy, cast(ceil(have * {length} * 0.4) as bigint) as low, cast(floor(have * {length} * 0.8) as bigint) as high from t join r on r.dataset = t.dataset and r.copy = t.copy and not own and rank = 0)
    select cast(dataset as int) as dataset, dataset || '-' || lpad(copy::varchar, 2, '0') as series_id,
    low + cast('0x' || substr(md5('{seed}:place:' || dataset || ':' || copy || ':0'), 1, 7) as bigint) % greatest(high - low, 1) + 1 as true_loc, cast({length} as int) as true_len from b"""
