"""Building blocks of the SQL equivalents: common table expressions as text."""

from __future__ import annotations

from neardup.config import DEFAULT
from neardup.functions.text import WORD_CLASS
from neardup.operators.terms import positions
from neardup.sources.fixtures import BANNER, FLIPS


def h32(*parts: str) -> str:
    """First eight hex digits of an md5 as a number; parts are SQL expressions."""
    return f"cast('0x' || substr(md5({' || chr(124) || '.join(f'cast({p} as varchar)' for p in parts)}), 1, 8) as bigint)"


def ham(a: str, b: str, words: int = 8) -> str:
    """Differing bits of two lists of words."""
    return f"cast(list_sum(list_transform(range(1, {words + 1}), lambda i: bit_count(xor({a}[i], {b}[i])))) as bigint)"


def shingles(source: str = "select doc_id as item_id, text from documents", name: str = "") -> str:
    """``tok`` and ``sh(item_id, s)``: distinct three-word shingles of a text source."""
    return f"""tok{name} as (select item_id, regexp_extract_all(lower(text), '{WORD_CLASS}') as t from ({source})),
sh{name} as (select distinct item_id, unnest(case when len(t) < 3 then [array_to_string(t, ' ')]
  else list_transform(range(1, len(t) - 1), lambda i: t[i] || ' ' || t[i+1] || ' ' || t[i+2]) end) as s from tok{name})"""


def signatures(source: str = "select doc_id as item_id, text from documents", name: str = "") -> str:
    """``sig(item_id, words)`` of a text source, with the shingles."""
    word = " + ".join(f"(case when 2 * sum((v >> {b}) & 1) > count(*) then {1 << b} else 0 end)" for b in range(32))
    return f"""{shingles(source, name)},
hx{name} as (select item_id, w, cast('0x' || substr(md5(cast(w // 4 as varchar) || '|' || s), cast(1 + 8 * (w % 4) as int), 8) as bigint) as v from sh{name}, range(8) r(w)),
word{name} as (select item_id, w, cast({word} as bigint) as x from hx{name} group by item_id, w),
sig{name} as (select item_id, list(x order by w) as words from word{name} group by item_id)"""


def vector_bits() -> str:
    """``vec(item_id, words)``: sign bits of the given vectors."""
    return """vec as (select vec_id as item_id, list_transform(range(0, 2), lambda w:
  cast(list_sum(list_transform(range(0, 32), lambda j: case when embedding[w * 32 + j + 1] > 0 then cast(1 as bigint) << j else 0 end)) as bigint)) as words from embeddings)"""


def group_value(words: str, start: int, width: int) -> str:
    """A group of bits as a number."""
    out, at, shift = [], start, 0
    while shift < width:
        off = at % 32
        take = min(32 - off, width - shift)
        out.append(f"((({words}[{at // 32 + 1}] >> {off}) & {(1 << take) - 1}) << {shift})")
        at, shift = at + take, shift + take
    return "(" + " + ".join(out) + ")"


def terms(source: str, bits: int, width: int, name: str = "terms") -> str:
    """``terms(item_id, term)`` of a signature table."""
    each = ", ".join(f"{g << width} + {group_value('words', g * width, width)}" for g in range(bits // width))
    return f"{name} as (select item_id, unnest([{each}]) as term from {source})"


def permuted_terms(source: str, bits: int, width: int, repeats: int, seed: int = 0, name: str = "terms") -> str:
    """``terms(item_id, term)`` of the permuted layout."""
    value = lambda at: " + ".join(f"(((words[{p // 32 + 1}] >> {p % 32}) & 1) << {j})" for j, p in enumerate(at))
    each = ", ".join(f"{g << width} + {value(at)}" for g, at in enumerate(positions(bits, width, repeats, seed)))
    return f"{name} as (select item_id, unnest([{each}]) as term from {source})"


def search_terms(source: str = "sig", name: str = "terms") -> str:
    """``terms(item_id, term)`` in the default layout, that of up to 4,096 items."""
    return permuted_terms(source, DEFAULT.bits, DEFAULT.width, DEFAULT.repeats, DEFAULT.seed, name)


def cands(min_overlap: int = 1, name: str = "cand", of: str = "terms") -> str:
    """``cand(a, b, overlap)``: pairs by shared terms."""
    return f"""{name} as (select x.item_id as a, y.item_id as b, count(*) as overlap from {of} x join {of} y on x.term = y.term and x.item_id < y.item_id
  group by x.item_id, y.item_id having count(*) >= {min_overlap})"""


def near(sig: str = "sig", max_distance: int = 64, words: int = 8, name: str = "near", of: str = "cand") -> str:
    """``near(a, b, overlap, distance)``."""
    return f"""{name} as (select * from (select c.a, c.b, c.overlap, {ham('x.words', 'y.words', words)} as distance from {of} c
  join {sig} x on x.item_id = c.a join {sig} y on y.item_id = c.b) where distance <= {max_distance})"""


def components(edges: str = "near", name: str = "comp") -> str:
    """``comp(item, component)`` of the nodes of edges ``(a, b)``. Needs ``with recursive``."""
    return f"""both_{name} as (select a as src, b as dst from {edges} union select b, a from {edges}),
reach_{name} as (select src as item, src as c from both_{name} union select e.dst, r.c from reach_{name} r join both_{name} e on e.src = r.item),
{name} as (select item, min(c) as component from reach_{name} group by item)"""


def cut(comp: str, sig: str, max_distance: int, rounds: int, words: int, seed: int = 0, order: str = "seeded", name: str = "cut") -> str:
    """``cut(item_id, head_id, value)``: the greedy cut, a fixed number of rounds (enough for the components at hand)."""
    by = {"seeded": f"md5('{seed}|' || cast(component as varchar) || '|' || cast(item_id as varchar))", "lowest": "item_id", "engagement": "(-weight, item_id)"}[order]
    more = ", weight" if order == "engagement" else ""
    out = [f"{name}_p1 as (select c.item as item_id, c.component, s.words{more} from {comp} c join {sig} s on s.item_id = c.item)"]
    for r in range(1, rounds + 1):
        out.append(
            f"""{name}_h{r} as (select component, arg_min(item_id, {by}) as head_id, arg_min(words, {by}) as hw from {name}_p{r} group by component),
{name}_j{r} as (select p.*, h.head_id, {ham('p.words', 'h.hw', words)} as value from {name}_p{r} p join {name}_h{r} h using (component)),
{name}_p{r + 1} as (select item_id, component, words{more} from {name}_j{r} where value > {max_distance})"""
        )
    done = " union all ".join(f"select item_id, head_id, value from {name}_j{r} where value <= {max_distance}" for r in range(1, rounds + 1))
    return ",\n".join([*out, f"{name} as ({done})"])


def near_items(sig: str = "sig", max_distance: int = 64, name: str = "near") -> str:
    """``near(a, b, overlap, distance)`` of a signature table with its ``terms``: equal bits are one item, its copies pairs of their own."""
    return f"""rp as (select words, min(item_id) as item_id from {sig} group by words),
rterms as (select * from terms where item_id in (select item_id from rp)),
{cands(1, 'rcand', 'rterms')},
{near('rp', max_distance, name='rnear', of='rcand')},
{name} as (select a, b, overlap, distance from rnear union all
  select r.item_id, s.item_id, {(DEFAULT.bits // DEFAULT.width) * (1 + DEFAULT.repeats)}, 0 from {sig} s join rp r on r.words = s.words where r.item_id <> s.item_id)"""


#: The documents' signatures, terms and candidate pairs at the default settings.
SEARCH = f"{signatures()},\n{search_terms()},\n{cands()}"
#: Their near pairs and components.
CLOSED = f"{SEARCH},\n{near_items()},\n{components()}"
#: The documents' clusters, closure and cut: heads, members and similarity; ``map`` has the items that stand alone as well.
CUT = f"""{CLOSED},
{cut('comp', 'sig', 64, 6, 8)},
full_map as (select item_id, head_id, 1 - value / 256.0 as score_to_head from cut union all
  select item_id, item_id, 1.0 from sig where item_id not in (select item_id from cut))"""
DOCS = f"{CUT},\nmap as (select item_id, head_id from full_map)"

EACH = "(select greatest(1, (select count(*) from events) // greatest(1, (select count(*) from documents))) as each_)"
DAYS = f"""days as (select d.doc_id as item_id, e.ts as arrival, cast(date_diff('day', date '2024-01-01', cast(e.ts as date)) as bigint) as day
  from documents d, {EACH}, events e where e.event_id = d.doc_id * each_)"""
BOOKMARKS = """bookmarks as (select e.event_id, e.ts, e.user_id, e.event_type as action, e.value as weight, d.doc_id as item_id, d.source as board
  from events e join documents d on d.doc_id = (e.event_id * 7919) % (select count(*) from documents))"""
SPAM = "spam as (select distinct doc_id as item_id from labels where quality = 0)"
LOCALE = """locale as (select c_custkey as user_id, n_name as nation, r_name as region, ['en', 'fr', 'de', 'es'][n_nationkey % 4 + 1] as lang
  from customer join nation on c_nationkey = n_nationkey join region on n_regionkey = r_regionkey)"""

_MASKED = "list_transform(range(0, 2), lambda w: xor(words[w + 1], cast(coalesce(list_sum(list_transform(list_filter(o, lambda p: p // 32 = w), lambda p: cast(1 as bigint) << cast(p % 32 as int))), 0) as bigint)))"


def drawn(*key: str) -> str:
    """The 64 positions in hash order, as a subquery over ``vec``-like rows aliased ``v`` with the key columns."""
    return f"(select list(p order by {h32(*key, 'p')}, p) from range(64) r(p))"


PLANT = f"""{vector_bits()},
plant0 as (select v.item_id as origin_id, v.words, f.no, f.flips, ({drawn('v.item_id', 'f.flips')})[1:f.flips] as o
  from vec v, (values {', '.join(f'({i}, {f})' for i, f in enumerate(FLIPS))}) f(no, flips)),
plant as (select 1000000 + origin_id * 10 + no as item_id, origin_id, flips, {_MASKED} as words from plant0)"""

DRIFT = f"""{vector_bits()},
drift0 as (select v.item_id as v, v.words, {drawn('v.item_id', "'drift'")} as d from vec v),
drift1 as (
  select v, words, 0 as no, 'head' as role, d[1:0] as o from drift0 union all select v, words, 1, 'member', d[1:6] from drift0
  union all select v, words, 2, 'member', d[7:12] from drift0 union all select v, words, 3, 'query', d[1:6] || d[13:18] from drift0
  union all select v, words, 4, 'query', d[7:12] || d[19:24] from drift0),
drift as (select 2000000 + v * 10 + no as item_id, 2000000 + v * 10 as head_id, role, {_MASKED} as words from drift1)"""

CHAIN = f"""{vector_bits()},
chain0 as (select x.words as words, list_filter(range(0, 64), lambda p: ((xor(x.words[p // 32 + 1], y.words[p // 32 + 1]) >> cast(p % 32 as int)) & 1) = 1) as d
  from vec x, vec y where x.item_id = 0 and y.item_id = 1),
chain1 as (select words, hop, d[1:hop * 4] as o from chain0, range(0, cast(ceil(len(d) / 4.0) as bigint) + 1) r(hop)),
chain as (select hop as item_id, {_MASKED} as words from chain1)"""

VARIANTS = f"""var0 as (select doc_id as origin_id, text, string_split(text, ' ') as w, len(string_split(text, ' ')) as n from documents),
var1 as (select * from var0 where n >= 60),
var2 as (
  select origin_id, 0 as no, 'crop' as kind, array_to_string(w[1:cast(floor(n * 0.8) as bigint)], ' ') as text from var1
  union all select origin_id, 1, 'flip', array_to_string(list_reverse(string_split(text, '. ')), '. ') from var1
  union all select origin_id, 2, 'rotate', array_to_string(w[cast(floor(n * 0.25) as bigint) + 1:n] || w[1:cast(floor(n * 0.25) as bigint)], ' ') from var1
  union all select origin_id, 3, 'scale', array_to_string([w[i] for i in range(1, n + 1) if (i - 1) % 10 <> 9], ' ') from var1
  union all select origin_id, 4, 'noise', array_to_string([case when {h32('origin_id', '(i - 1)')} % 25 = 0 then 'noise' else w[i] end for i in range(1, n + 1)], ' ') from var1
  union all select origin_id, 5, 'overlay', text || ' {BANNER}' from var1),
variants as (select 1000000 + origin_id * 10 + no as item_id, origin_id, kind, text from var2)"""

TRUTH = """shn as (select item_id, count(*) as n from sh group by item_id),
shc as (select x.item_id as a, y.item_id as b, count(*) as c from sh x join sh y on x.s = y.s and x.item_id < y.item_id group by x.item_id, y.item_id),
truth as (select a, b, c / (p.n + q.n - c) as jaccard from shc join shn p on p.item_id = a join shn q on q.item_id = b where c / (p.n + q.n - c) >= 0.5)"""

GOLD = f"""{SEARCH},
{TRUTH},
{components('truth', 'tc')},
wanted as (select cast(round(count(*) * 86 / 14.0) as bigint) as w from truth),
near_no as (select a, b from (select c.a, c.b, row_number() over (order by {h32("'n'", 'c.a', 'c.b')}, c.a, c.b) as r from cand c anti join truth t on t.a = c.a and t.b = c.b), wanted where r <= w // 2),
far0 as (select distinct least(x, y) as a, greatest(x, y) as b from (select doc_id as x, (doc_id * 7919 + 17) % (select count(*) from documents) as y from documents) where x <> y),
far1 as (select f.a, f.b from far0 f anti join truth t on t.a = f.a and t.b = f.b),
far2 as (select f.a, f.b from far1 f anti join cand t on t.a = f.a and t.b = f.b),
far_no as (select a, b from (select a, b, row_number() over (order by {h32("'f'", 'a', 'b')}, a, b) as r from far2), wanted where r <= w - w // 2),
gold0 as (select a, b, 1 as truth from truth union all select a, b, 0 from near_no union all select a, b, 0 from far_no),
gold1 as (select *, [{', '.join(f"case when {h32('a', 'b', str(j))} % 100 < 5 then 1 - truth else truth end" for j in range(5))}] as votes from gold0),
gold2 as (select *, case when list_sum(votes) >= 3 then 1 else 0 end as label from gold1),
gold3 as (select g.*, {h32("'s'", 'coalesce(p.component, a)')} % 2 as ha, {h32("'s'", 'coalesce(q.component, b)')} % 2 as hb from gold2 g left join tc p on p.item = a left join tc q on q.item = b),
gold as (select a, b, truth, votes, label, case when ha <> hb then 'mixed' when ha = 0 then 'train' else 'test' end as split from gold3)"""

#: Places of three-word runs, and of candidate pairs the votes for each offset.
RUNS = f"""toks as (select doc_id as item_id, regexp_extract_all(lower(text), '{WORD_CLASS}') as t from documents),
runs as (select item_id, unnest(range(0, greatest(len(t) - 2, 1))) as pos, t from toks),
pts0 as (select item_id, pos, cast('0x' || substr(md5(array_to_string(t[pos + 1:pos + 3], ' ')), 1, 15) as bigint) as h from runs),
pts as (select item_id, h, min(pos) as pos from pts0 group by item_id, h)"""
VOTES = RUNS + """,
votes as (select c.a, c.b, y.pos - x.pos as off, count(*) as v from cand c join pts x on x.item_id = c.a join pts y on y.item_id = c.b and y.h = x.h group by all)"""


def with_(*parts: str) -> str:
    """A ``with recursive`` clause."""
    return "with recursive " + ",\n".join(parts) + "\n"
