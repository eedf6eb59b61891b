"""DuckDB counterparts of the linkage queries, on lists of bit places and rows (record, place).

Written from the description of the registers and of the measures; it shares no code and no value with the operators.
"""

from __future__ import annotations

QIDS = ("given", "surname", "suburb", "postcode")
# The syllables, and the tables of the corruptor.
ONE = "ba ce di fo gu ha je ki lo mu na pe ri so tu va".split()
TWO = "ber cal din fos gar hen jul kam lin mor nel pat ros sten tol vik".split()
LOOKS = "o0 l1 s5 b8 g9 z2".split()
LOOKS2 = [("m", "rn"), ("w", "vv"), ("d", "cl"), ("h", "li"), ("u", "v"), ("n", "ri"), ("e", "c"), ("i", "j")]
SOUND = [("ph", "f"), ("ck", "k"), ("c", "k"), ("z", "s"), ("ie", "y"), ("th", "t"), ("gh", "g"), ("sch", "sh"), ("ei", "ai"), ("v", "w"), ("nn", "n"), ("tt", "t"), ("en", "an"), ("er", "ar")]


def _list(items) -> str:
    return "[" + ",".join(f"'{x}'" for x in items) + "]"


def _hex(text: str, at: int, n: int = 1) -> str:
    return f"('0x'||substr({text},{at},{n}))::BIGINT"


def _pick(items, text: str, at: int) -> str:
    return f"({_list(items)})[{_hex(text, at)}+1]"


def _fit(length: int, p: int) -> int:
    return -(-length // p) * p


def people(source: str, p: int, where: str = "true", name: str = "reg") -> str:
    """CTEs ending in `name`: party, rid, entity and the attributes. source: entity, nation."""
    return f"""{name}_k AS (SELECT entity, nation, md5('e'||entity::VARCHAR) AS e, md5('n'||nation::VARCHAR) AS n, (entity % {p + 1})::INT AS r FROM ({source}) WHERE {where}),
{name} AS (SELECT party::INT AS party, chr(64+party::INT)||'-'||entity::VARCHAR AS rid, entity,
 {_pick(ONE, "e", 1)}||{_pick(TWO, "e", 2)} AS given, {_pick(TWO, "e", 3)}||{_pick(ONE, "e", 4)}||{_pick(TWO, "e", 5)} AS surname,
 {_pick(TWO, "n", 1)}||{_pick(ONE, "n", 2)}||'ton' AS suburb, (20000+nation*389+{_hex("e", 6)})::VARCHAR AS postcode
 FROM {name}_k, range(1,{p + 1}) t(party) WHERE r=0 OR r=party)"""


CUSTOMERS = "SELECT c_custkey AS entity, c_nationkey AS nation FROM customer"


def reg(p: int = 3, where: str = "true") -> str:
    return people(CUSTOMERS, p, where)


def _draw(*parts: str) -> str:
    return _hex("md5(concat_ws('|','',%s))" % ",".join(parts), 1, 8)


def _rules(table) -> str:
    return "[" + ",".join(f"{{'f':'{x}','t':'{y}'}}" for a, b in table for x, y in ((a, b), (b, a))) + "]"


def _rewritten(c: str, table, draw: str) -> str:
    fit = f"list_filter({_rules(table)}, lambda r: contains({c}, r.f))"
    one = f"({fit})[({draw} % len({fit}))::INT+1]"
    return f"CASE WHEN len({fit})=0 THEN {c} ELSE substr({c},1,strpos({c},{one}.f)-1)||{one}.t||substr({c},strpos({c},{one}.f)+length({one}.f)) END"


def dirty(p: int, rate: int, name: str = "reg") -> str:
    """CTEs that replace `name` by its corrupted form `dirty`, with `corrupted` and up to three edits."""
    looks = [tuple(x) for x in LOOKS] + LOOKS2
    out = [f"""{name}_s0 AS (SELECT *, (entity % {p + 1}=0) AND ({_draw("'c'", "entity")} % 100 < {rate}) AND (((1+{_draw("'m'", "entity")} % {2**p - 2}) >> (party-1)) & 1)=1 AS corrupted,
 1+{_draw("'n'", "entity", "party")} % 3 AS edits FROM {name})"""]
    for step in (1, 2, 3):
        d = {k: _draw(f"'{k}'", "entity", "party", str(step)) for k in "aopsr"}
        cols = []
        for i, q in enumerate(QIDS):
            at = f"(1+dp % greatest(length({q}),1))::INT"
            sign = "chr((48+ds % 10)::INT)" if q == "postcode" else "chr((97+ds % 26)::INT)"
            words = (q, q) if q == "postcode" else (_rewritten(q, looks, "dr"), _rewritten(q, SOUND, "dr"))
            forms = [f"substr({q},1,{at}-1)||{sign}||substr({q},{at})", f"substr({q},1,{at}-1)||substr({q},{at}+1)", f"substr({q},1,{at}-1)||{sign}||substr({q},{at}+1)", f"substr({q},1,{at}-1)||substr({q},{at}+1,1)||substr({q},{at},1)||substr({q},{at}+2)", *words]
            cases = " ".join(f"WHEN dk={k} THEN {f}" for k, f in enumerate(forms))
            cols.append(f"CASE WHEN NOT corrupted OR edits<{step} OR da<>{i} THEN {q} {cases} END AS {q}")
        out.append(f"{name}_d{step} AS (SELECT *, {d['a']} % 4 AS da, {d['o']} % 6 AS dk, {d['p']} AS dp, {d['s']} AS ds, {d['r']} AS dr FROM {name}_s{step - 1})")
        out.append(f"{name}_s{step} AS (SELECT party, rid, entity, corrupted, edits, {', '.join(cols)} FROM {name}_d{step})")
    return ",\n".join([*out, f"{name}_dirty AS (SELECT party, rid, entity, {','.join(QIDS)}, corrupted FROM {name}_s3)"])


def soundex(c: str) -> str:
    """Digits by letter (others break runs), h and w transparent after the first sign, runs once, vowels out, four signs."""
    code = f"translate(regexp_replace(lower({c}),'[^a-z]','a','g'),'abcdefghijklmnopqrstuvwxyz','01230127022455012623017202')"
    rest = f"substr({code},1,1)||replace(substr({code},2),'7','')"
    for d in "0123456":
        rest = f"regexp_replace({rest},'{d}+','{d}','g')"
    tail = f"replace(substr({rest},2),'0','')"
    return f"CASE WHEN {c}='' THEN '' WHEN NOT regexp_matches(substr({c},1,1),'[A-Za-z]') THEN {c} ELSE rpad(substr(upper(substr({c},1,1))||{tail},1,4),4,'0') END"


def key(cols=("surname",), fn: str = "soundex") -> str:
    forms = {"soundex": soundex, "exact": lambda c: c, "prefix:4": lambda c: f"substr({c},1,4)", "prefix:24": lambda c: f"substr({c},1,24)"}
    return "concat_ws('|'," + ",".join(forms[fn](c) for c in cols) + ")" if cols else "''"


def spec_key(p: int) -> str:
    return key(("surname",) if p == 3 else ("given", "surname"))


def grams(source: str, q: int = 2, qids=QIDS, longest: int = 240) -> str:
    """CTE g: party, rid, attr, gram."""
    values = ",".join(f"{{'attr':{i},'v':lower(trim(coalesce({c},''),' '))}}" for i, c in enumerate(qids))
    return f"g AS (SELECT DISTINCT party, rid, a.attr AS attr, substr(a.v,i::INT,{q}) AS gram FROM (SELECT party, rid, unnest([{values}]) AS a FROM {source}), range(1,{longest}) t(i) WHERE i <= length(a.v)-{q - 1})"


def place(bits: int, secret: str = "") -> str:
    return f"{_hex(f"md5('{secret}|'||i::VARCHAR||'|'||gram)", 1, 8)} % {bits}"


def pos(bits: int, k: int) -> str:
    return f"dict AS (SELECT DISTINCT gram, ({place(bits)})::INT AS p FROM (SELECT DISTINCT gram FROM g), range(0,{k}) t(i)), pos AS (SELECT DISTINCT party, rid, p FROM g JOIN dict USING (gram))"


def filters(source: str, block: str, p: int = 3, length: int = 500, k: int = 20, q: int = 2, qids=QIDS, enc: str | None = None) -> str:
    """CTEs g, pos, e: party, rid, b (block), v (sorted places), x, tk (token of the record)."""
    bits = _fit(length, p)
    return f"""{grams(source, q, qids)},
{enc or pos(bits, k)},
v AS (SELECT party, rid, list_sort(list(p)) AS v, count(*) AS x FROM pos GROUP BY party, rid),
e AS (SELECT s.party, s.rid, {block} AS b, coalesce(v.v,[]) AS v, coalesce(v.x,0) AS x, substr(sha256('rid||'||s.rid),1,32) AS tk FROM {source} s LEFT JOIN v ON s.party=v.party AND s.rid=v.rid)"""


def _and(lists: list[str]) -> str:
    out = lists[0]
    for x in lists[1:]:
        out = f"list_intersect({out},{x})"
    return out


def sets(p: int, name: str = "t") -> str:
    """CTE t: r1.., tk1.., v1.., x1.., b, cand, c, x of every candidate."""
    cols = ", ".join(f"e{j}.rid AS r{j}, e{j}.tk AS tk{j}, e{j}.v AS v{j}, e{j}.x AS x{j}" for j in range(1, p + 1))
    cand = "||','||".join(f"e{j}.rid" for j in range(1, p + 1))
    toks = "||','||".join(f"e{j}.tk" for j in range(1, p + 1))
    joins = " ".join(f"JOIN e e{j} ON e1.b=e{j}.b AND e{j}.party={j}" for j in range(2, p + 1))
    return f"{name} AS MATERIALIZED (SELECT e1.b AS b, {cols}, {cand} AS cand, {toks} AS tk, len({_and([f'e{j}.v' for j in range(1, p + 1)])})::BIGINT AS c, ({'+'.join(f'e{j}.x' for j in range(1, p + 1))})::BIGINT AS x FROM e e1 {joins} WHERE e1.party=1)"


def standard(p: int = 3, source: str = "reg", pre: str | None = None, block: str | None = None, **more) -> str:
    return f"WITH {pre or reg(p)},\n{filters(source, block or spec_key(p), p, **more)},\n{sets(p)}"


def hits(p: int, num: int = 4, den: int = 5) -> str:
    return f"SELECT cand, c, x, round({p}*c/x,6) AS sim FROM t WHERE x>0 AND {den}*{p}*c >= {num}*x"


def held(p: int, width: int, num: int = 4, den: int = 5, how: str = "prefix", first_small: bool = False) -> str:
    """CTE kept: holder, cand, tk, c, x of the candidates that each holder keeps; how: all, prefix, final, bound."""
    out = []
    for h in range(1, p + 1):
        order = [h] + [j for j in range(1, p + 1) if j != h]
        piece = {j: f"list_filter(v{j}, lambda q: q//{width}={h - 1})" for j in order}
        cols = ", ".join(f"{piece[j]} AS s{j}" for j in order)
        src = f"(SELECT *, {cols} FROM t)"

        def tests(order=order) -> str:
            out = []
            for n in range(2, p + 1):
                c = f"len({_and([f's{j}' for j in order[:n]])})"
                size = "+".join(f"len(s{j})" for j in order[:n])
                if how == "prefix" or how == "final" and n == p:
                    out.append(f"{den}*{n}*{c} >= {num}*({size})")
                if how == "bound":
                    out.append(f"{den}*{p}*{c} >= {num}*({size}+{p - n}*{c})")
            return " AND ".join(out) or "true"

        test = tests()
        if first_small:  # three parties: the two others swap where the later one has the smaller block
            a, b = order[1], order[2]
            size = lambda j: f"(SELECT count(*) FROM e WHERE party={j} AND e.b=z.b)"
            test = f"CASE WHEN {size(b)}<{size(a)} THEN {tests([h, b, a])} ELSE {test} END"
        c = f"len({_and([f's{j}' for j in range(1, p + 1)])})"
        out.append(f"SELECT {h} AS holder, cand, tk, {c}::BIGINT AS c, x{h}::BIGINT AS x FROM {src} z WHERE {test}")
    return "kept AS MATERIALIZED (" + " UNION ALL ".join(out) + ")"


def filtered(p: int) -> str:
    w = _fit(500, p) // p
    return f"{standard(p)}, {held(p, w)}, ok AS (SELECT cand FROM kept GROUP BY cand HAVING count(*)={p}) {hits(p)} AND cand IN (SELECT cand FROM ok)"


M60 = 1 << 60


def _mask(key_: str, kind: str) -> str:
    return _hex(f"md5({key_}||'|{kind}|'||tk)", 1, 15)


def _ring(who: str) -> str:
    first = {"one": "1", "rotate": f"({_hex("md5('first|'||tk)", 1, 8)} % 3 + 1)::INT", "external": "0"}[who]
    base = f"{standard(3)}, {held(3, 167, how='all')}"
    if who == "external":
        part = lambda kind: f"((({kind}+{_mask("'k1|'||holder::VARCHAR", kind)}-{_mask("'k1|'||((holder+1)%3+1)::VARCHAR", kind)}) % {M60}) + {M60}) % {M60}"
        return f"{base} SELECT tk AS cand, 0 AS first, 1 AS hop, holder AS sender, 0 AS receiver, {part('c')} AS masked_c, {part('x')} AS masked_x FROM kept"
    run = lambda kind: f"((sum({kind}) OVER (PARTITION BY tk ORDER BY hop))::BIGINT+{_mask("'k1|'||first::VARCHAR", kind)}) % {M60}"
    return f"""{base}, f AS (SELECT *, {first} AS first FROM kept), h AS (SELECT *, ((holder-first+3) % 3 + 1)::INT AS hop FROM f)
SELECT tk AS cand, first, hop, holder AS sender, (holder % 3 + 1)::INT AS receiver, {run('c')} AS masked_c, {run('x')} AS masked_x FROM h"""


def _score(found: str, truth: str, extra: str = "") -> str:
    return f"""SELECT {extra} count(*) FILTER (m=1 AND t=1) AS tp, count(*) FILTER (t IS NULL) AS fp, count(*) FILTER (m IS NULL) AS fn,
 round(count(*) FILTER (m=1 AND t=1)/nullif(count(m),0),6) AS precision, round(count(*) FILTER (m=1 AND t=1)/nullif(count(t),0),6) AS recall,
 round(2*count(*) FILTER (m=1 AND t=1)/nullif(count(m)+count(t),0),6) AS f1
 FROM (SELECT cand, 1 AS m FROM ({found})) FULL JOIN (SELECT cand, 1 AS t FROM ({truth})) USING (cand)"""


def truth(p: int, source: str = "reg") -> str:
    return f"SELECT string_agg(rid,',' ORDER BY rid) AS cand FROM {source} GROUP BY entity HAVING count(*)={p}"


def _grid(p: int) -> str:
    """All rates side by side, each with its own blocks."""
    pre = [reg(p)]
    for rate in (0, 20, 40):
        pre.append(dirty(p, rate).replace("reg_", f"d{rate}_"))
    union = " UNION ALL ".join(f"SELECT party, '{r}:'||rid AS rid, entity, {','.join(QIDS)}, {r} AS rate FROM d{r}_dirty" for r in (0, 20, 40))
    block = f"s.rate::VARCHAR||'|'||{spec_key(p)}"
    w = _fit(500, p) // p
    head = f"{standard(p, 'many', ',\n'.join([*pre, f'many AS ({union})']), block)}, {held(p, w)}, ok AS (SELECT cand FROM kept GROUP BY cand HAVING count(*)={p}), tr AS (SELECT rate, string_agg(rid,',' ORDER BY rid) AS cand FROM many GROUP BY rate, entity HAVING count(*)={p})"
    found = {"approx": hits(p), "approx_filtered": f"{hits(p)} AND cand IN (SELECT cand FROM ok)", "exact": f"SELECT cand FROM t WHERE {' AND '.join(f'v1=v{j}' for j in range(2, p + 1))}"}
    rows = []
    for mode, sql_ in found.items():
        for r in (0, 20, 40):
            rows.append(_score(f"SELECT cand FROM ({sql_}) WHERE split_part(cand,':',1)='{r}'", f"SELECT cand FROM tr WHERE rate={r}", f"'{mode}' AS mode, {p} AS parties, {r} AS rate,"))
    return head + " " + " UNION ALL ".join(rows)


def segments(source: str, p: int, length: int, k: int) -> str:
    """CTE piece: holder, owner, rid, tk, s (places inside the piece as text)."""
    w = _fit(length, p) // p
    return f"""{filters(source, "''", p, length, k)},
piece AS MATERIALIZED (SELECT h::INT AS holder, party AS owner, rid, tk, coalesce(array_to_string(list_filter(v, lambda q: q//{w}=h-1),' '),'') AS s FROM e, range(1,{p + 1}) t(h))"""


def _attack() -> str:
    """Pieces of the registers beside those of the global side, the customers with even keys, P=7."""
    world = people(CUSTOMERS, 7, "entity % 2=0", "wreg")
    a = segments("reg", 7, 100, 3)
    b = segments("wreg", 7, 100, 3)
    for name in ("g", "dict", "pos", "v", "e", "piece"):
        import re

        b = re.sub(rf"\b{name} AS ", f"w{name} AS ", b)
        b = re.sub(rf"(FROM|JOIN) {name}\b", rf"\1 w{name}", b)
    b = b.replace("v.party", "wv.party").replace("v.rid", "wv.rid").replace("coalesce(v.v", "coalesce(wv.v").replace("coalesce(v.x", "coalesce(wv.x")
    return f"WITH {reg(7)}, {a}, {world}, {b}"


def _disclosure(p: int, length: int, k: int) -> str:
    return f"""SELECT {p} AS parties, {_fit(length, p)} AS l, {k} AS k, round(count(*)/sum(n),6) AS dr_mean, round(count(*) FILTER (n=1)/sum(n),6) AS dr_mark, max(round(1/n,6)) AS dr_max
 FROM (WITH {reg(p)}, {segments("reg", p, length, k)} SELECT holder, owner, s, count(*) AS n FROM piece GROUP BY ALL)"""


def _sens(length: int, k: int, q: int, p: int = 3) -> str:
    bits = _fit(length, p)
    return f"""WITH {reg(p)}, {grams("reg", q)}, {pos(bits, k)}, dd AS (SELECT p, count(*) AS dist FROM dict GROUP BY p), ff AS (SELECT p, count(*) AS freq FROM pos GROUP BY p)
SELECT i AS place, coalesce(dist,0) AS dist, coalesce(freq,0) AS freq, round(1/least(dist,freq),6) AS s FROM range(0,{bits}) t(i) LEFT JOIN dd ON dd.p=i LEFT JOIN ff ON ff.p=i"""


def _sampled(weights) -> str:
    """CTE pos of the sampled encoding: record places dealt by weight in digest order, each drawing a source place."""
    bits = 501
    share = [bits * w // sum(weights) for w in weights]
    for i in range(bits - sum(share)):
        share[i] += 1
    ends = [sum(share[: i + 1]) for i in range(4)]
    attr = " ".join(f"WHEN n<={e} THEN {i}" for i, e in enumerate(ends))
    return f"""smp AS (SELECT j, CASE {attr} END AS attr, {_hex("md5('|draw|'||j::VARCHAR)", 1, 8)} % {bits} AS src FROM (SELECT j, row_number() OVER (ORDER BY md5('|order|'||j::VARCHAR), j) AS n FROM range(0,{bits}) t(j))),
apos AS (SELECT DISTINCT party, rid, attr, {place(bits)} AS p FROM g, range(0,20) t(i)),
pos AS (SELECT DISTINCT a.party, a.rid, j::INT AS p FROM apos a JOIN smp ON a.attr=smp.attr AND a.p=smp.src)"""


def _weighted(weights) -> str:
    share = [80 * w // sum(weights) for w in weights]
    for i in range(80 - sum(share)):
        share[i] += 1
    k = " ".join(f"WHEN {i} THEN {n}" for i, n in enumerate(share))
    return f"pos AS (SELECT DISTINCT party, rid, ({place(501)})::INT AS p FROM g, range(0,{max(share)}) t(i) WHERE i < CASE attr {k} END)"


W = (2, 3, 1, 2)


def sql() -> dict[str, str]:
    out = {}
    for p in (3, 5, 7):
        out[f"register_p{p}"] = f"WITH {reg(p)} SELECT party, rid, entity, given, surname, suburb, postcode FROM reg"
        out[f"dice_multi_p{p}"] = out[f"match_approx_p{p}"] = f"{standard(p)} {hits(p)}"
        out[f"match_filtered_p{p}"] = filtered(p)
        out[f"quality_grid_p{p}"] = _grid(p)
        w = _fit(500, p) // p
        words = -(-w // 63)
        rows = [("approx", "n.n", 16 * p), ("approx_filtered", "f.n", 16 * p), ("exact", "n.n", 8 * words * p + 8 * words * p * p)]
        out[f"cost_compare_p{p}"] = f"{standard(p)}, {held(p, w)}, n AS (SELECT count(*) AS n FROM t), f AS (SELECT count(*) AS n FROM (SELECT cand FROM kept GROUP BY cand HAVING count(*)={p})) " + " UNION ALL ".join(f"SELECT '{m}' AS mode, {p} AS parties, {c} AS candidates, {c}*{b} AS bytes FROM n, f" for m, c, b in rows)
    orders = f"SELECT o_orderkey AS entity, ({_hex("md5('nat'||o_orderkey::VARCHAR)", 1, 8)} % 25)::INT AS nation FROM orders"
    out["register_orders"] = f"WITH {people(orders, 3)} SELECT party, count(*) AS n, count(*) FILTER (entity % 4=0) AS shared, count(DISTINCT given||' '||surname) AS names FROM reg GROUP BY party"
    out["register_products"] = "SELECT party::INT AS party, chr(64+party::INT)||'-'||p_partkey::VARCHAR AS rid, p_partkey AS entity, p_name AS name, p_brand AS brand, p_type AS kind, p_size::VARCHAR AS size FROM part, range(1,4) t(party) WHERE p_partkey % 4=0 OR p_partkey % 4=party"
    out["size_series"] = f"WITH {reg()} SELECT size::INT AS size, party, count(*) AS n, count(*) FILTER (entity % 4=0) AS shared FROM reg, (VALUES (500),(1000),(1500)) s(size) WHERE entity<=size GROUP BY size, party"
    out["true_sets"] = f"WITH {reg()} {truth(3)}"
    for rate in (20, 40):
        out[f"corrupt_{rate}"] = f"WITH {reg()}, {dirty(3, rate)} SELECT party, rid, entity, {','.join(QIDS)}, corrupted FROM reg_dirty"
    looks = [tuple(x) for x in LOOKS] + LOOKS2
    ops = {"insert": "substr(p_name,1,2)||'x'||substr(p_name,3)", "delete": "substr(p_name,1,2)||substr(p_name,4)", "substitute": "substr(p_name,1,2)||'x'||substr(p_name,4)", "transpose": "substr(p_name,1,2)||substr(p_name,4,1)||substr(p_name,3,1)||substr(p_name,5)", "ocr": _rewritten("p_name", looks, "p_partkey"), "phonetic": _rewritten("p_name", SOUND, "p_partkey")}
    out["corrupt_ops"] = " UNION ALL ".join(f"SELECT p_partkey, '{n}' AS op, p_name AS before, {e} AS after FROM part" for n, e in ops.items())
    out["corrupt_rate_audit"] = f"""WITH {reg()}, {dirty(3, 20)}, per AS (SELECT entity, max(corrupted::INT) AS d, count(*) FILTER (NOT corrupted) AS clean FROM reg_dirty WHERE entity % 4=0 GROUP BY entity)
SELECT round(sum(d)/count(*),6) AS share, min(clean) AS min_clean, (SELECT count(*) FROM reg a JOIN reg_dirty b USING (party, rid) WHERE NOT corrupted AND (a.given,a.surname,a.suburb,a.postcode) IS DISTINCT FROM (b.given,b.surname,b.suburb,b.postcode)) AS wrong FROM per"""
    for name, q, value in (("2", 2, "lower(trim(p_name,' '))"), ("3", 3, "lower(trim(p_name,' '))"), ("padded", 2, "'_'||lower(trim(p_name,' '))||'_'")):
        out[f"qgrams_{name}"] = f"SELECT DISTINCT p_partkey, substr(v,i::INT,{q}) AS gram FROM (SELECT p_partkey, {value} AS v FROM part), range(1,80) t(i) WHERE i<=length(v)-{q - 1}"
    words = "g AS (SELECT DISTINCT substr(v,i::INT,2) AS gram FROM (SELECT lower(trim(p_name,' ')) AS v FROM part), range(1,80) t(i) WHERE i<=length(v)-1)"
    for name, secret in (("independent", ""), ("keyed", "key")):
        out[f"positions_{name}"] = f"WITH {words} SELECT gram, i::INT AS i, {place(501, secret)} AS pos FROM g, range(0,20) t(i)"
    out["positions_double"] = f"WITH {words} SELECT gram, i::INT AS i, ({_hex('md5(gram)', 1, 8)}+i*{_hex('md5(gram)', 9, 8)}) % 501 AS pos FROM g, range(0,20) t(i)"
    out["bloom_string"] = f"""WITH g AS (SELECT DISTINCT p_partkey, substr(v,i::INT,2) AS gram FROM (SELECT p_partkey, lower(trim(p_name,' ')) AS v FROM part), range(1,80) t(i) WHERE i<=length(v)-1), q AS (SELECT DISTINCT p_partkey, {place(501)} AS p FROM g, range(0,20) t(i))
SELECT p_partkey, string_agg(p::VARCHAR,' ' ORDER BY p) AS positions, count(*)::INT AS ones FROM q GROUP BY p_partkey"""
    shown = "SELECT party, rid, array_to_string(v,' ') AS places, x::INT AS x_own FROM e"
    for name, enc in (("shared", None), ("sampled", _sampled(W)), ("weighted", _weighted(W))):
        out[f"encode_{name}"] = f"WITH {reg()}, {filters('reg', spec_key(3), enc=enc)} {shown}"
        if enc:
            out[f"match_{name}"] = f"{standard(3, 'reg_dirty', reg() + ', ' + dirty(3, 20), enc=enc)} {hits(3)}"
    out["encode_attribute"] = f"""WITH {reg()}, {grams("reg")}, ap AS (SELECT DISTINCT party, rid, attr, {place(501)} AS p FROM g, range(0,20) t(i))
SELECT party, rid, ({_list(QIDS)})[attr+1] AS attr, string_agg(p::VARCHAR,' ' ORDER BY p) AS places, count(*)::INT AS ones FROM ap GROUP BY party, rid, attr"""
    out["weights"] = f"""WITH {reg()}, {dirty(3, 20)}, val AS (SELECT party, entity, unnest([{','.join(f"{{'attr':'{q}','v':{q}}}" for q in QIDS)}]) AS a FROM reg_dirty),
mm AS (SELECT x.a.attr AS attr, count(*) AS pairs, count(*) FILTER (x.a.v=y.a.v) AS agree FROM val x JOIN val y ON x.entity=y.entity AND x.a.attr=y.a.attr AND y.party=x.party+1 GROUP BY 1),
uu AS (SELECT attr, sum(n*n) AS sq, sum(n) AS al FROM (SELECT a.attr AS attr, a.v AS v, count(*) AS n FROM val GROUP BY ALL) GROUP BY attr)
SELECT attr, round(agree/pairs,6) AS m, round(sq::DOUBLE/(al::DOUBLE*al),6) AS u, round(log2((agree/pairs)/(sq::DOUBLE/(al::DOUBLE*al))),6) AS w FROM mm JOIN uu USING (attr)"""
    base = f"WITH {reg()}, {filters('reg', spec_key(3))}"
    out["segments"] = f"{base} SELECT party, rid, h::INT AS piece, coalesce(array_to_string(list_transform(list_filter(v, lambda q: q//167=h-1), lambda q: q-167*(h-1)),' '),'') AS places, len(list_filter(v, lambda q: q//167=h-1))::INT AS seg_ones FROM e, range(1,4) t(h)"
    out["exchange"] = f"{base} SELECT h::INT AS holder, party AS owner, count(*) AS rows, max(len(list_filter(v, lambda q: q//167=h-1)))::INT AS max_bits, 167 AS width FROM e, range(1,4) t(h) GROUP BY h, party"
    noise = f"{base}, fl AS (SELECT party, rid, i::INT AS p FROM e, range(0,501) t(i) WHERE {_hex("md5('|'||rid||'|'||i::VARCHAR)", 1, 8)} % 100 < 5), both_ AS (SELECT party, rid, p FROM fl INTERSECT SELECT party, rid, p FROM pos), per AS (SELECT e.party, e.rid, (SELECT count(*) FROM fl WHERE fl.rid=e.rid)::INT AS flipped, (x+(SELECT count(*) FROM fl WHERE fl.rid=e.rid)-2*(SELECT count(*) FROM both_ b WHERE b.rid=e.rid))::INT AS x_after FROM e)"
    out["perturb"] = f"{noise} SELECT party, rid, flipped, x_after FROM per"
    out["perturbed_fill"] = f"{noise} SELECT party, count(*) AS n, round(sum(x_after)/(count(*)*501),6) AS fill FROM per GROUP BY party"
    out["tokens"] = f"WITH {reg()} SELECT rid, substr(sha256('rid||'||rid),1,32) AS rid_token, substr(sha256('bkv||'||{spec_key(3)}),1,32) AS bkv_token FROM reg"
    out["encrypted_ids"] = f"WITH {reg()} SELECT rid, rid AS opened, true AS hidden FROM reg"
    out["bloom_theory"] = f"""{base}, m AS (SELECT (SELECT count(*) FROM (SELECT DISTINCT party, rid, gram FROM g))/count(*) AS q, sum(x)/(count(*)*501) AS fill FROM e)
SELECT round(q,6) AS q_avg, round(501/q*ln(2),6) AS k_opt, round(pow(pow(2,-ln(2)),501/q),6) AS f_opt, round(pow(1-exp(-20*q/501),20),6) AS f_k, round(1-exp(-20*q/501),6) AS fill_exp, round(fill,6) AS fill_obs FROM m"""
    out["fill_ratio"] = f"{base} SELECT party, count(*) AS n, round(sum(x)/(count(*)*501),6) AS fill FROM e GROUP BY party"
    for name, cols, fn in (("surname", ("surname",), "soundex"), ("compound", ("given", "surname"), "soundex"), ("prefix", ("surname",), "prefix:4"), ("exact", ("surname",), "exact"), ("none", (), "exact")):
        out[f"block_{name}"] = f"WITH {reg()} SELECT party, {key(cols, fn)} AS bkv, count(*) AS n FROM reg GROUP BY 1, 2"
    cand = lambda k: f"SELECT a.rid||','||b.rid||','||c.rid AS cand FROM (SELECT rid, {k} AS k FROM reg WHERE party=1) a JOIN (SELECT rid, {k} AS k FROM reg WHERE party=2) b USING (k) JOIN (SELECT rid, {k} AS k FROM reg WHERE party=3) c USING (k)"
    out["candidates"] = f"WITH {reg()} {cand(key())}"
    out["block_multipass"] = f"WITH {reg()} {cand(key(('given', 'surname')))} UNION {cand(key(('surname',), 'prefix:4'))}"
    ns = ", ".join(f"count(*) FILTER (party={j}) AS n{j}" for j in (1, 2, 3))
    out["shared_blocks"] = f"WITH {reg()} SELECT {key()} AS bkv, {ns} FROM reg GROUP BY 1 HAVING count(DISTINCT party)=3"
    prod = lambda k: f"(SELECT {k} AS b, party FROM part, range(1,4) t(party) WHERE p_partkey % 4=0 OR p_partkey % 4=party)"
    out["block_guard"] = f"SELECT b AS bkv, (n1*n2*n3)::DOUBLE AS sets, CASE WHEN n1*n2*n3>5000 THEN 'split' ELSE 'keep' END AS action FROM (SELECT b, {ns} FROM {prod('p_name')} GROUP BY b) WHERE n1*n2*n3>0"
    out["block_split"] = f"WITH o AS (SELECT b FROM (SELECT b, {ns} FROM {prod('p_name')} GROUP BY b) WHERE n1*n2*n3>5000), cut AS (SELECT CASE WHEN p_name IN (SELECT b FROM o) THEN p_name||'/'||p_brand ELSE p_name END AS b, party FROM part, range(1,4) t(party) WHERE p_partkey % 4=0 OR p_partkey % 4=party) SELECT b AS bkv, (n1*n2*n3)::DOUBLE AS sets, n1+n2+n3 AS rows FROM (SELECT b, {ns} FROM cut GROUP BY b) WHERE n1*n2*n3>0"
    series = []
    for p in (3, 5, 7):
        for cols in (("surname",), ("given", "surname")):
            prod_ = "*".join(f"(count(*) FILTER (party={j}))::DOUBLE" for j in range(1, p + 1))
            series.append(f"SELECT size, {p} AS parties, '{'+'.join(cols)}' AS keys, sum(n) AS candidates FROM (WITH {reg(p)} SELECT size::INT AS size, {key(cols)} AS k, {prod_} AS n FROM reg, (VALUES (500),(1000),(1500)) s(size) WHERE entity<=size GROUP BY 1, 2) GROUP BY size")
    out["candidate_count"] = " UNION ALL ".join(series)
    out["rr"] = f"WITH {reg()} SELECT c::DOUBLE AS candidates, round(1-c/f,6) AS rr FROM (SELECT count(*) AS c FROM ({cand(key())})), (SELECT product(n) AS f FROM (SELECT count(*) AS n FROM reg GROUP BY party))"
    std = standard(3)
    out["dice_pairs"] = f"{base} SELECT a.rid AS rid1, b.rid AS rid2, len(list_intersect(a.v,b.v))::INT AS c, a.x::INT AS x1, b.x::INT AS x2, round(2*len(list_intersect(a.v,b.v))/(a.x+b.x),6) AS dice FROM e a JOIN e b ON a.b=b.b WHERE a.party=1 AND b.party=2"
    out["match_rotate"] = out["match_external"] = f"{std} {hits(3)}"
    kinds = {"jaccard": "c/len(list_distinct(list_concat(list_concat(v1,v2),v3)))", "overlap": "c/least(x1,x2,x3)", "cosine": "c/pow(x1::DOUBLE*x2*x3,1/3)"}
    for kind, e in kinds.items():
        out[f"sim_{kind}"] = f"{std} SELECT cand, round({e},6) AS sim FROM t WHERE {e} >= 0.8-2e-13"
    every = f"{std}, {held(3, 167, how='all')}"
    out["dice_distributed"] = f"{every} SELECT tk AS cand, {', '.join(f'sum(c) FILTER (holder={h})::BIGINT AS c{h}' for h in (1, 2, 3))}, sum(c)::BIGINT AS c, sum(x)::BIGINT AS x FROM kept GROUP BY tk"
    rows = "SELECT holder, tk AS cand, c, x FROM kept"
    out["partial_counts"] = out["filter_zero"] = f"{every} {rows}"
    out["filter_st"] = f"{std}, {held(3, 167)} {rows}"
    out["filter_loose"] = f"{std}, {held(3, 167, 3, 5)} {rows}"
    out["filter_final"] = f"{std}, {held(3, 167, how='final')} {rows}"
    out["filter_order"] = f"{std}, {held(3, 167, first_small=True)} {rows}"
    out["filter_bound"] = f"{std}, {held(3, 167, how='bound')}, al AS (SELECT DISTINCT tk FROM kept), {held(3, 167, how='all').replace('kept AS', 'full_ AS')} SELECT holder, tk AS cand, c, x FROM full_ WHERE tk IN (SELECT tk FROM al)"
    out["match_bound"] = f"{std} {hits(3)}"
    out["ring_example"] = f"WITH {reg()}, n AS (SELECT party, count(*) AS n FROM reg GROUP BY party) SELECT party::INT AS hop, party::INT AS sender, (party%3+1)::INT AS receiver, (sum(n) OVER (ORDER BY party)+20)::BIGINT AS message FROM n UNION ALL SELECT 4, 1, 1, sum(n)::BIGINT FROM n"
    for who, name in (("one", "transcript"), ("rotate", "rotate"), ("external", "external")):
        out[f"ring_{name}"] = _ring(who)
    out["ring_modular"] = f"{std} SELECT tk AS cand, c, x, c AS c_one, x AS x_one, c AS c_rotate, x AS x_rotate, c AS c_external, x AS x_external FROM t"
    cut = f"CASE WHEN {key()} IN (SELECT k FROM (SELECT k, {ns} FROM (SELECT party, {key()} AS k FROM reg) GROUP BY k) WHERE n1*n2*n3>500) THEN {key()}||'/'||given ELSE {key()} END"
    out["match_split"] = f"{standard(3, block=cut)} {hits(3)}"
    subs = []
    for chosen in ((1, 2), (1, 3), (2, 3), (1, 2, 3)):
        m = len(chosen)
        a = chosen[0]
        joins = " ".join(f"JOIN e e{j} ON e{a}.b=e{j}.b AND e{j}.party={j}" for j in chosen[1:])
        c, x = f"len({_and([f'e{j}.v' for j in chosen])})", "(" + "+".join(f"e{j}.x" for j in chosen) + ")"
        subs.append(f"SELECT '{'+'.join(map(str, chosen))}' AS subset, {"||','||".join(f'e{j}.rid' for j in chosen)} AS cand, round({m}*{c}/{x},6) AS sim FROM e e{a} {joins} WHERE e{a}.party={a} AND 5*{m}*{c} >= 4*{x}")
    out["match_subsets"] = f"{base} " + " UNION ALL ".join(subs)
    ranks = ", ".join(f"row_number() OVER (PARTITION BY r{j} ORDER BY round(3*c/x,6) DESC, cand) AS k{j}" for j in (1, 2, 3))
    out["match_best"] = f"{std}, h AS (SELECT cand, c, x, round(3*c/x,6) AS sim, {ranks} FROM t WHERE 15*c>=4*x) SELECT cand, c, x, sim FROM h WHERE k1=1 AND k2=1 AND k3=1"
    out["match_topk"] = f"{std}, h AS (SELECT b AS bkv, (row_number() OVER (PARTITION BY b ORDER BY round(3*c/x,6) DESC, cand))::INT AS rank, cand, round(3*c/x,6) AS sim FROM t WHERE 15*c>=4*x) SELECT bkv, rank, cand, sim FROM h WHERE rank<=2"
    soiled = standard(3, "reg_dirty", reg() + ", " + dirty(3, 20))
    out["match_exact"] = out["match_exact_equal"] = f"{soiled} SELECT cand FROM t WHERE v1=v2 AND v2=v3"
    out["match_exact_register"] = f"WITH {reg()}, {filters('reg', spec_key(3), length=3000, k=1)}, o AS (SELECT p FROM (SELECT DISTINCT party, p FROM pos) GROUP BY p HAVING count(*)=3) SELECT party, rid FROM e WHERE NOT EXISTS (SELECT 1 FROM pos WHERE pos.rid=e.rid AND pos.party=e.party AND pos.p NOT IN (SELECT p FROM o))"
    out["match_clear"] = f"WITH {reg()}, {dirty(3, 20)} SELECT a.rid||','||b.rid||','||c.rid AS cand FROM reg_dirty a JOIN reg_dirty b USING ({','.join(QIDS)}) JOIN reg_dirty c USING ({','.join(QIDS)}) WHERE a.party=1 AND b.party=2 AND c.party=3"
    clear = "pos AS (SELECT DISTINCT party, rid, gram AS p FROM g)"
    out["match_qgram_clear"] = f"{standard(3, enc=clear)} {hits(3)}"
    out["match_noblock"] = f"{standard(3, pre=reg(3, 'entity<20'), block=chr(39) * 2)} {hits(3)}"
    out["length_filter"] = f"{std} SELECT count(*) AS candidates, count(*) FILTER (15*least(x1,x2,x3)>=4*x) AS kept, round(count(*) FILTER (15*least(x1,x2,x3)>=4*x)/count(*),6) AS share FROM t"
    out["range_partners"] = f"{base} SELECT a.rid AS rid1, b.rid AS rid2, a.x::INT AS x1, b.x::INT AS x2 FROM e a JOIN e b ON a.b=b.b WHERE a.party=1 AND b.party=2 AND b.x>=ceil(a.x*4/6) AND b.x<=floor(a.x*6/4)"
    out["rr_f"] = f"""{std}, {held(3, 167)}, b AS (SELECT count(*)::DOUBLE AS n FROM t), h AS (SELECT holder, count(*)::DOUBLE AS k FROM kept GROUP BY holder), al AS (SELECT holder, k FROM h UNION ALL SELECT 0, avg(k) FROM h UNION ALL SELECT -1, count(*) FROM (SELECT cand FROM kept GROUP BY cand HAVING count(*)=3))
SELECT holder, round(k,6) AS kept, n AS before, round(1-k/n,6) AS rr_f FROM al, b"""
    many = " UNION ALL ".join(f"SELECT party, '{n}:'||rid AS rid, entity, {','.join(QIDS)}, {n} AS size FROM reg WHERE entity<={n}" for n in (500, 1000, 1500))
    out["rr_f_series"] = f"""{standard(3, 'many', reg() + f', many AS ({many})', "s.size::VARCHAR||'|'||" + key())}, {held(3, 167)},
nb AS (SELECT split_part(b,'|',1)::INT AS size, count(*) AS n FROM t GROUP BY 1), nk AS (SELECT split_part(cand,':',1)::INT AS size, holder, count(*) AS k FROM kept GROUP BY 1, 2)
SELECT nb.size, h::INT AS holder, n AS before, coalesce(k,0) AS kept, round(1-coalesce(k,0)/n,6) AS rr_f FROM nb CROSS JOIN range(1,4) r(h) LEFT JOIN nk ON nk.size=nb.size AND nk.holder=h"""
    pairs = lambda s: " UNION ".join(f"SELECT split_part(cand,',',{i})||','||split_part(cand,',',{j}) AS cand FROM ({s})" for i, j in ((1, 2), (1, 3), (2, 3)))
    out["quality_pairwise"] = f"{soiled} {_score(pairs(hits(3)), pairs(truth(3)))}"
    inside = f"SELECT string_agg(rid,',' ORDER BY rid) AS cand FROM (SELECT rid, entity, {key()} AS k FROM reg_dirty) GROUP BY entity HAVING count(*)=3 AND count(DISTINCT k)=1"
    out["quality_within_blocks"] = f"{soiled} {_score(hits(3), inside)}"
    att = _attack()
    out["suspicion"] = f"{att}, w AS (SELECT holder, s, count(*) AS n FROM wpiece GROUP BY ALL) SELECT p.holder, p.owner, p.tk AS token, coalesce(n,0) AS n_g, round(coalesce(1/n,0),6) AS p_s FROM piece p LEFT JOIN w ON p.holder=w.holder AND p.s=w.s"
    out["disclosure_external"] = f"{att}, w AS (SELECT holder, s, count(*) AS n FROM wpiece GROUP BY ALL) SELECT p.holder, round(avg(coalesce(1/n,0)),6) AS dr_mean, round(count(*) FILTER (n=1)/count(*),6) AS dr_mark, max(round(coalesce(1/n,0),6)) AS dr_max FROM piece p LEFT JOIN w ON p.holder=w.holder AND p.s=w.s GROUP BY p.holder"
    word = "list_sum(list_transform(list_filter([try_cast(y AS BIGINT) FOR y IN string_split(s,' ')], lambda y: y IS NOT NULL), lambda y: 1::BIGINT << (y % 15)::INT))"
    rank = lambda src, n: f"SELECT holder, s, count(*) AS {n}, row_number() OVER (PARTITION BY holder ORDER BY count(*) DESC, coalesce({word},0)) AS rank FROM {src} GROUP BY holder, s"
    out["freq_attack"] = f"{att}, a AS ({rank('piece', 'n')}), b AS ({rank('wpiece', 'g')}) SELECT a.holder, count(*) AS patterns, count(g) AS hits, coalesce(sum(n) FILTER (g IS NOT NULL),0)::BIGINT AS records FROM a LEFT JOIN b ON a.holder=b.holder AND a.rank=b.rank AND a.s=b.s GROUP BY a.holder"
    grid = [(3, 100, 3), (5, 100, 3), (7, 100, 3), (10, 100, 3), (20, 100, 3), (3, 500, 20), (7, 500, 9)]
    out["disclosure_grid"] = " UNION ALL ".join(_disclosure(*g) for g in grid)
    out["bit_sensitivity"] = _sens(500, 20, 2)
    out["param_simulation"] = " UNION ALL ".join(f"SELECT {_fit(n, 3)} AS l, {h} AS k, {q} AS q, count(*) FILTER (freq=0) AS unset, max(s) AS s_max, round(avg(s),6) AS s_mean, count(*) FILTER (s=1) AS s_one FROM ({_sens(n, h, q)})" for n, h, q in ((500, 20, 2), (500, 9, 2), (1000, 5, 3)))
    sweep = []
    for n, h in ((500, 20), (500, 9), (200, 9), (100, 3)):
        bits = _fit(n, 3)
        w = bits // 3
        pre = f"{reg()}, {dirty(3, 20)}, {filters('reg_dirty', key(('given', 'surname')), 3, n, h)}, {sets(3)}"
        risk = f"SELECT round(count(*)/sum(m),6) FROM (SELECT h, party, list_filter(v, lambda q: q//{w}=h-1) AS s, count(*) AS m FROM e, range(1,4) r(h) GROUP BY ALL)"
        sweep.append(f"SELECT * FROM (WITH {pre} SELECT {bits} AS l, {h} AS k, (SELECT round(sum(x)/(count(*)*{bits}),6) FROM e) AS fill, ({risk}) AS dr_mean, (SELECT f1 FROM ({_score(hits(3), truth(3))})) AS f1)")
    out["tradeoff_sweep"] = " UNION ALL ".join(sweep)
    out["ledger"] = f"""{std}, {held(3, 167)}, n AS (SELECT count(*) AS n FROM (SELECT cand FROM kept GROUP BY cand HAVING count(*)=3))
SELECT 'exchange' AS step, 6::BIGINT AS messages, (SELECT 2*count(*)*85 FROM e) AS bytes UNION ALL SELECT 'ring', 3*n, 48*n FROM n UNION ALL SELECT 'results', 2*n, 16*n FROM n"""
    out["cost_model"] = f"""{std}, a AS (SELECT count(*) AS al, count(DISTINCT b) AS b FROM e), gg AS (SELECT count(*) AS g FROM (SELECT DISTINCT party, rid, gram FROM g)), cc AS (SELECT count(*) AS c FROM t)
SELECT round(al/3,3) AS n, b AS blocks, round(g/al,3) AS grams, g*20 AS hash_ops, round(al/3*3*(g/al)*20,3) AS hash_model, round(c*6::DOUBLE,3) AS ands, round(b*pow(al/3/b,3)*6,3) AS ands_model FROM a, gg, cc"""
    out["memory_model"] = f"{std} SELECT h::INT AS holder, (SELECT count(*)*92 FROM e) AS piece_bytes, (SELECT count(*)*112 FROM t) AS list_bytes FROM range(1,4) r(h)"
    out["initiator_view"] = f"{every} SELECT tk AS cand, sum(c) FILTER (holder>1)::BIGINT AS rest_c, sum(x) FILTER (holder>1)::BIGINT AS rest_x, 334 AS c_high, 2 AS x_low, 1002 AS x_high, sum(c) FILTER (holder>1)>0 AS shares_bits FROM kept GROUP BY tk"
    steps = []
    for t_ in (0, 6, 7, 8):
        k = f"kept{t_}"
        steps.append(f"SELECT {t_} AS tenths, (SELECT count(*) FROM ok{t_}) AS kept, count(*) AS matches, count(*) FILTER (cand IN (SELECT cand FROM tr)) AS tp, round(count(*) FILTER (cand IN (SELECT cand FROM tr))/(SELECT count(*) FROM tr),6) AS recall FROM ({hits(3)} AND cand IN (SELECT cand FROM ok{t_}))")
    helds = ", ".join(f"{held(3, 167, t_, 10).replace('kept AS', f'kept{t_} AS')}, ok{t_} AS (SELECT cand FROM kept{t_} GROUP BY cand HAVING count(*)=3)" for t_ in (0, 6, 7, 8))
    out["smx_sweep"] = f"{soiled}, tr AS ({truth(3)}), {helds} " + " UNION ALL ".join(steps)
    few = key(("given", "surname"))
    out["running_example"] = f"""{standard(3, block=few)}, {held(3, 167, how="all")} SELECT cand, {", ".join(f"sum(c) FILTER (holder={h})::BIGINT AS c{h}" for h in (1, 2, 3))}, sum(c)::BIGINT AS c, sum(x)::BIGINT AS x,
round(3*sum(c)/sum(x),4) AS sim, 15*sum(c)>=4*sum(x) AS is_match FROM kept GROUP BY cand"""
    short = lambda t: held(3, 4, t, 10).replace("kept AS", f"kept{t} AS")
    left = lambda t: f"SELECT {t} AS tenths, h::INT AS holder, (SELECT count(*) FROM t) AS before, CASE WHEN h=0 THEN (SELECT count(*) FROM (SELECT cand FROM kept{t} GROUP BY cand HAVING count(*)=3)) ELSE (SELECT count(*) FROM kept{t} WHERE holder=h) END AS kept FROM range(0,4) r(h)"
    out["filter_example"] = f"{standard(3, block=few, length=12, k=1)}, {short(6)}, {short(8)} {left(6)} UNION ALL {left(8)}"
    two = lambda c: f"(SELECT list_sort(list(DISTINCT ('0x'||substr(md5('|'||i::VARCHAR||'|'||substr(lower(trim({c},' ')),j::INT,2)),1,8))::BIGINT % 14)) FROM range(0,2) t(i), range(1,80) r(j) WHERE j<length(trim({c},' ')))"
    out["two_strings"] = f"""SELECT p_partkey, array_to_string(a,' ') AS p1, array_to_string(b,' ') AS p2, len(a)::INT AS x1, len(b)::INT AS x2, len(list_intersect(a,b))::INT AS c, round(2*len(list_intersect(a,b))/(len(a)+len(b)),4) AS dice
FROM (SELECT p_partkey, {two('p_name')} AS a, {two('p_type')} AS b FROM part)"""
    qids = ("name", "brand", "kind", "size")
    preg = f"reg AS ({out['register_products']})"
    pk = "concat_ws('|',name,brand)"
    cut = f"CASE WHEN {pk} IN (SELECT k FROM (SELECT k, {ns} FROM (SELECT party, {pk} AS k FROM reg) GROUP BY k) WHERE n1*n2*n3>200) THEN {pk}||'/'||kind ELSE {pk} END"
    out["link_products"] = f"{standard(3, pre=preg, block=cut, qids=qids)} {hits(3, 19, 20)}"
    docs = "reg AS (SELECT (doc_id % 3+1)::INT AS party, chr(65+(doc_id % 3)::INT)||'-'||doc_id::VARCHAR AS rid, substr(lower(trim(regexp_replace(coalesce(text,''),'[ \\t\\r\\n]+',' ','g'),' ')),1,200) AS head, coalesce(lang,'') AS lang FROM documents)"
    out["link_documents"] = f"{standard(3, pre=docs, block='substr(head,1,24)', qids=('head', 'lang'), length=2000, k=6)} {hits(3, 9, 10)}"
    vec = "e AS (SELECT (vec_id % 3+1)::INT AS party, chr(65+(vec_id % 3)::INT)||'-'||vec_id::VARCHAR AS rid, label AS b, '' AS tk, list_filter(range(0,len(embedding)), lambda i: embedding[i+1]>0) AS v, len(list_filter(embedding, lambda q: q>0)) AS x FROM embeddings WHERE label IS NOT NULL AND embedding IS NOT NULL)"
    out["link_embeddings"] = f"WITH {vec}, {sets(3)} {hits(3, 1, 2)}"
    return out
