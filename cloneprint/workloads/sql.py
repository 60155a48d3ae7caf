"""Pieces of SQL that the twins of several queries share (DuckDB dialect)."""

import re

WORD, TOKEN, END = r"\w+", r"\w+|[^\w\s]", r"[.!?]+\s*"
P = str((1 << 61) - 1)

LINES = """lines as (select * from (select doc_id, source, lang, unnest(string_split(text, chr(10))) as line, unnest(range(len(string_split(text, chr(10))))) as pos from documents) where line <> '')"""
SENTENCES = rf"""sents as (select * from (select doc_id, source, pos, lower(trim(unnest(string_split_regex(line, '{END}')))) as s from lines) where s <> '')"""
B_SENTENCES = rf"""b_lines as (select * from (select item_id, unnest(string_split(text, chr(10))) as line from benchmark) where line <> ''),
b_sents as (select * from (select item_id, lower(trim(unnest(string_split_regex(line, '{END}')))) as s from b_lines) where s <> '')"""


def h(x: str) -> str:
    """60 bits of md5."""
    return f"cast(('0x' || substr(md5({x}), 1, 15)) as bigint)"


def mod(x: str) -> str:
    return f"cast(cast({x} as hugeint) % {P} as bigint)"


def bag(text: str) -> str:
    """Sum of the hashes of a text's tokens."""
    return mod(f"coalesce(list_sum(list_transform(regexp_extract_all({text}, '{TOKEN}'), lambda t: cast({h('t')} as hugeint))), 0)")


def volume(text: str) -> str:
    t = f"regexp_extract_all(lower({text}), '{TOKEN}')"
    return f"(len({t}) * log2(cast(greatest(len(list_distinct({t})), 1) as double)))"


def cyclomatic(text: str) -> str:
    return f"(1 + length(regexp_replace({text}, '[^,;]', '', 'g')))"


def loc(text: str) -> str:
    return f"greatest(len(list_filter(string_split_regex({text}, '{END}'), lambda x: trim(x) <> '')), 1)"


def complexity(text: str, variant: str = "log") -> str:
    v, n = volume(text), loc(text)
    if variant == "log":
        v, n = f"ln(greatest({v}, 1.0))", f"ln(greatest(cast({n} as double), 1.0))"
    return f"(5.2 * {v} + 0.23 * {cyclomatic(text)} + 16.2 * {n})"


NORMAL = lambda text: f"md5(regexp_replace({text}, '\\s+', '', 'g'))"
NAME = rf"case when length(lower(regexp_extract(line, '{WORD}'))) >= 4 then lower(regexp_extract(line, '{WORD}')) end"
CALLS = rf"""fns as (select doc_id, pos, line, {NAME} as name, {loc('line')} as loc, {bag('lower(line)')} as own from lines),
named as (select doc_id, name, min(pos) as callee from fns where name is not null group by all),
uses as (select doc_id, pos as caller, w as name, count(*) as k from (select doc_id, pos, unnest(regexp_extract_all(lower(line), '{WORD}')[2:]) as w from lines) where length(w) >= 4 group by all),
calls as (select doc_id, caller, callee, cast(sum(k) as bigint) as n from uses join named using (doc_id, name) group by all)"""
ACYCLIC = """plain as materialized (select * from calls where caller <> callee),
reach as (select doc_id, caller as a, callee as b from plain union select r.doc_id, r.a, p.callee from reach r join plain p on r.doc_id = p.doc_id and r.b = p.caller),
degree as (select doc_id, caller as fn, count(*) as deg from plain group by all),
ranks as (select f.doc_id, f.pos as fn, coalesce(d.deg, 0) as deg, f.loc from fns f left join degree d on d.doc_id = f.doc_id and d.fn = f.pos),
acyclic as (select p.doc_id, p.caller, p.callee, p.n,
 case when r.a is not null and (x.deg < y.deg or (x.deg = y.deg and (x.loc < y.loc or (x.loc = y.loc and p.caller > p.callee)))) then 'cut' else 'keep' end as status
 from plain p left join reach r on r.doc_id = p.doc_id and r.a = p.callee and r.b = p.caller
 join ranks x on x.doc_id = p.doc_id and x.fn = p.caller join ranks y on y.doc_id = p.doc_id and y.fn = p.callee
 union all select doc_id, caller, callee, n, 'recursive' from calls where caller = callee)"""


def linked(marked: str = "acyclic", recursion: str = "site") -> str:
    """CTEs that end in ``linked`` (doc_id, fn, linked); calls that are not kept come from ``marked``."""
    times = "cast(n as hugeint)" if recursion == "site" else "case when status = 'recursive' then cast(1 as hugeint) else n end"
    return f"""parts as materialized (select f.doc_id, f.pos as fn, {mod("f.own + coalesce(m.marks, 0)")} as part from fns f
 left join (select doc_id, caller, sum({times} * case when status = 'recursive' then {h("'RECURSIVE'")} else {h("'EXTERNAL'")} end) as marks from {marked} where status <> 'keep' group by all) m on m.doc_id = f.doc_id and m.caller = f.pos),
kept as materialized (select doc_id, caller, callee, n from acyclic where status = 'keep'),
paths as (select doc_id, fn as top, fn, cast(1 as hugeint) as k from parts union all select p.doc_id, p.top, e.callee, p.k * e.n from paths p join kept e on e.doc_id = p.doc_id and e.caller = p.fn),
linked as (select p.doc_id, p.top as fn, {mod('sum(p.k * q.part)')} as linked from paths p join parts q on q.doc_id = p.doc_id and q.fn = p.fn group by all)"""


LINKED = linked()
CLASS_PRINT = mod("sum(cast(linked as hugeint) + " + h("'FUNCTION'") + ") + " + h("'CLASS'"))


def detector(pre: str, lines: str, real: str = "true", linking: bool = True) -> str:
    """CTEs that end in ``<pre>prints`` (doc_id, print) of the units in the CTE ``lines`` (doc_id, pos, line); ``real`` tells functions that are not trivial."""
    if not linking:
        text = f"prints as (select doc_id, {mod('sum(cast(own as hugeint) + ' + h(chr(39) + 'FUNCTION' + chr(39)) + ') + ' + h(chr(39) + 'CLASS' + chr(39)))} as print from (select doc_id, {bag('lower(line)')} as own from {lines} where {real}) group by doc_id)"
    else:
        first = re.sub(r"\b(fns|calls)\b", r"\g<1>0", CALLS).replace("from lines", f"from {lines}")
        text = f"""{first}, fns as materialized (select * from fns0 where {real}),
calls as materialized (select c.* from calls0 c join fns a on a.doc_id = c.doc_id and a.pos = c.caller join fns b on b.doc_id = c.doc_id and b.pos = c.callee), {ACYCLIC},
marked as (select * from acyclic union all select c.doc_id, c.caller, c.callee, c.n, 'external' from calls0 c join fns a on a.doc_id = c.doc_id and a.pos = c.caller left join fns b on b.doc_id = c.doc_id and b.pos = c.callee where b.pos is null),
{linked('marked')},
prints as (select doc_id, {CLASS_PRINT} as print from linked l where not exists (select 1 from kept k where k.doc_id = l.doc_id and k.callee = l.fn) group by doc_id)"""
    return re.sub(r"\b(fns0?|named|uses|calls0?|plain|reach|degree|ranks|acyclic|marked|parts|kept|paths|linked|prints)\b", rf"{pre}\1", text) if pre else text


def grams(w: str, k: int = 3) -> str:
    return f"list_sort(list_distinct(list_transform(range(1, len({w}) - {k} + 2), lambda i: array_to_string({w}[i:i + {k - 1}], ' '))))"


def shingled(where: str = "true") -> str:
    """CTEs that end in ``similar_pairs`` (a, b, c, na, nb): similar classes of lines by their smallest ids; an id is doc_id * 2**32 + pos."""
    return rf"""sets as materialized (select doc_id * 4294967296::hugeint + pos as id, doc_id, pos, source, {grams('w')} as g from (select *, regexp_extract_all(lower(line), '{WORD}') as w from lines where {where}) where len(w) >= 3),
groups as materialized (select min(id) as rep, count(*) as n_members, g from sets group by g),
posting as (select rep, len(g) as n, unnest(g) as x from groups),
shared as (select a.rep as a, b.rep as b, a.n as na, b.n as nb, count(*) as c from posting a join posting b on a.x = b.x and a.rep < b.rep group by all),
similar_pairs as materialized (select a, b, round(c / (na + nb - c), 6) as sim from shared where 10 * c >= 7 * (na + nb - c))"""


SHINGLED = shingled()
PAIR = "cast(a // 4294967296 as bigint) as a_doc, cast(a % 4294967296 as int) as a_pos, cast(b // 4294967296 as bigint) as b_doc, cast(b % 4294967296 as int) as b_pos"


def calls(pre: str, lines: str) -> str:
    """CTEs that end in ``<pre>calls`` of the units in the CTE ``lines`` (doc_id, pos, line)."""
    return re.sub(r"\b(fns|named|uses|calls)\b", rf"{pre}\1", CALLS.replace("from lines", f"from {lines}"))


def pagerank(edges: str, rounds: int = 20, d: float = 0.85, nodes: str = "", pre: str = "") -> str:
    """CTEs that end in ``<pre>r<rounds>`` (component, node, size, rank) from a CTE ``edges`` (component, src, dst), and one of more ``nodes``."""
    more = f" union select component, node from {nodes}" if nodes else ""
    out = f"""{pre}e as materialized (select component, src, dst, count(*) over (partition by component, src) as o from (select distinct component, src, dst from {edges})),
{pre}nodes as materialized (select component, node, count(*) over (partition by component) as size from (select component, src as node from {pre}e union select component, dst from {pre}e{more})),
{pre}users as materialized (select distinct component, src as node from {pre}e),
{pre}r0 as materialized (select component, node, size, 1.0::double / size as rank from {pre}nodes)"""
    for k in range(rounds):
        out += f""",
{pre}l{k} as materialized (select r.component, sum(case when u.node is null then r.rank else 0 end) as loose from {pre}r{k} r left join {pre}users u using (component, node) group by all),
{pre}g{k} as materialized (select e.component, e.dst as node, sum(r.rank / e.o) as got from {pre}e e join {pre}r{k} r on r.component = e.component and r.node = e.src group by all),
{pre}r{k + 1} as materialized (select n.component, n.node, n.size, {1 - d} / n.size + {d} * (coalesce(g.got, 0) + l.loose / n.size) as rank from {pre}nodes n left join {pre}g{k} g using (component, node) join {pre}l{k} l using (component))"""
    return out


def central(pre: str, rounds: int = 20) -> str:
    """The CTE ``<pre>central`` (component, node) of the more central half after ``pagerank``."""
    return f"{pre}central as materialized (select component, node from (select component, node, percent_rank() over (partition by component order by round(rank, 12) desc) as pct from {pre}r{rounds}) where pct <= 0.5)"
