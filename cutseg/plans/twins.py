"""DuckDB SQL of the shared steps, as common table expressions by name."""

from __future__ import annotations

TEST = "('src16', 'src17', 'src18', 'src19')"
DEV = "('src14', 'src15')"


def _sentences(name: str, source: str, keep: str) -> str:
    return (f"{name} as (select doc_id || ':' || sent_no as sent_id, doc_id, sent_no, {keep}, raw, regexp_replace(raw, '\\s+', '', 'g') as s from "
            f"(select doc_id, {keep}, unnest(range(0, len(u))) as sent_no, unnest(u) as raw from (select doc_id, {keep}, regexp_split_to_array(lower(text), '[.!?\\n]+') as u from {source}))"
            f" where regexp_replace(raw, '\\s+', '', 'g') <> '')")


def _grams(name: str, source: str, n: int) -> str:
    return f"{name} as (select lang, substr(s, i, {n}) as g, count(*) as cnt from (select lang, s, unnest(range(1, length(s) - {n} + 2)) as i from {source}) group by all)"


_OK = lambda *names: " and ".join(f"regexp_matches({c}, '^\\p{{L}}$')" for c in names)


def _z(name: str, grams: str) -> str:
    return f"{name} as (select lang, g, ln(cnt) / case when sd > 0 then sd else 1 end as z from {grams} join (select lang, stddev_samp(ln(cnt)) as sd from {grams} group by lang) using (lang))"


def _bi(name: str, grams: str, z: str) -> str:
    return (f"{name} as (select lang, substr(g, 1, 1) as a, substr(g, 2, 1) as b, cnt, z, case when {_OK('substr(g, 1, 1)', 'substr(g, 2, 1)')} then cnt / sum(cnt) over (partition by lang, substr(g, 1, 1)) else 0.0 end as p1"
            f" from {grams} join {z} using (lang, g))")


def _tri(name: str, grams: str, z: str) -> str:
    part = lambda cols: f"case when ok then cnt / sum(cnt) over (partition by lang, {cols}) else 0.0 end"
    return (f"{name} as (select lang, a, b, c, cnt, z, {part('a, b')} as f2, {part('b, c')} as b2, {part('a')} as pair from (select lang, substr(g, 1, 1) as a, substr(g, 2, 1) as b, substr(g, 3, 1) as c, cnt, z,"
            f" {_OK('substr(g, 1, 1)', 'substr(g, 2, 1)', 'substr(g, 3, 1)')} as ok from {grams} join {z} using (lang, g)))")


def _windows(name: str, source: str) -> str:
    return (f"{name} as (select sent_id, lang, i - 1 as i, case when i > 1 then substr(s, i - 1, 1) else '' end as o, substr(s, i, 1) as a, substr(s, i + 1, 1) as b, substr(s, i + 2, 1) as x"
            f" from (select sent_id, lang, s, unnest(range(1, length(s))) as i from {source}))")


def _edges(name: str, win: str, bi: str, tri: str) -> str:
    return (f"{name} as (select w.sent_id, w.lang, w.i, w.a, w.b, greatest(coalesce(p.p1, 0), coalesce(f.f2, 0), coalesce(r.b2, 0)) * coalesce(p.z, 0) as w from {win} w"
            f" left join {bi} p on p.lang = w.lang and p.a = w.a and p.b = w.b left join {tri} f on f.lang = w.lang and f.a = w.o and f.b = w.a and f.c = w.b"
            f" left join {tri} r on r.lang = w.lang and r.a = w.a and r.b = w.b and r.c = w.x)")


def _skips(name: str, win: str, tri: str) -> str:
    return (f"{name} as (select w.sent_id, w.lang, w.i, w.a, w.b, w.x as c, coalesce(t.pair * t.z, 0) as w from {win} w left join {tri} t on t.lang = w.lang and t.a = w.a and t.b = w.b and t.c = w.x where w.x <> '')")


TOKEN = "[\\p{L}\\p{N}]+|[^\\s\\p{L}\\p{N}]"
#: name -> (definition, what it needs)
CTE: dict[str, tuple[str, tuple[str, ...]]] = {
    "docs": ("docs as (select doc_id, text, lang, source from documents where text is not null qualify row_number() over (partition by text order by doc_id) = 1)", ()),
    "train_docs": (f"train_docs as (select * from docs d where source not in {TEST} and source not in {DEV} and not exists (select 1 from benchmark b where contains(d.text, b.text)))", ("docs",)),
    "test_docs": (f"test_docs as (select * from docs where source in {TEST})", ("docs",)),
    "dev_docs": (f"dev_docs as (select * from docs where source in {DEV})", ("docs",)),
    "all_sents": (_sentences("all_sents", "docs", "lang, source"), ("docs",)),
    "train": (_sentences("train", "train_docs", "lang, source"), ("train_docs",)),
    "test": (_sentences("test", "test_docs", "lang, source"), ("test_docs",)),
    "bench": (_sentences("bench", "(select item_id as doc_id, text, 'en' as lang from benchmark)", "lang"), ()),
    "part_names": ("part_names as (select distinct lower(p_name) as sent_id, 'part' as lang, lower(p_name) as raw, regexp_replace(lower(p_name), '\\s+', '', 'g') as s from part)", ()),
    **{k: (_grams(k, "train", n), ("train",)) for n, k in ((1, "uni_g"), (2, "bi_g"), (3, "tri_g"))},
    **{k: (_grams(k, "part_names", n), ("part_names",)) for n, k in ((2, "pbi_g"), (3, "ptri_g"))},
    "z2": (_z("z2", "bi_g"), ("bi_g",)), "z3": (_z("z3", "tri_g"), ("tri_g",)), "pz2": (_z("pz2", "pbi_g"), ("pbi_g",)), "pz3": (_z("pz3", "ptri_g"), ("ptri_g",)),
    "bi": (_bi("bi", "bi_g", "z2"), ("z2",)), "tri": (_tri("tri", "tri_g", "z3"), ("z3",)),
    "pbi": (_bi("pbi", "pbi_g", "pz2"), ("pz2",)), "ptri": (_tri("ptri", "ptri_g", "pz3"), ("pz3",)),
    "win": (_windows("win", "test"), ("test",)), "pwin": (_windows("pwin", "part_names"), ("part_names",)),
    "edges": (_edges("edges", "win", "bi", "tri"), ("win", "bi", "tri")), "pedges": (_edges("pedges", "pwin", "pbi", "ptri"), ("pwin", "pbi", "ptri")),
    "skips": (_skips("skips", "win", "tri"), ("win", "tri")), "pskips": (_skips("pskips", "pwin", "ptri"), ("pwin", "ptri")),
    "words": ("words as (select lang, word, count(*) as cnt from (select lang, unnest(regexp_extract_all(raw, '" + TOKEN + "')) as word from train) where regexp_matches(word, '^\\p{L}+$') group by all)", ("train",)),
    "lexicon": ("lexicon as (select lang, word, cnt, row_number() over (partition by lang order by cnt desc, word) as rank from words)", ("words",)),
    "sets": ("sets as (select w.lang, w.word as ch, case when w.cnt / u.cnt >= 0.5 then 2 else 1 end as set_id from words w join uni_g u on u.lang = w.lang and u.g = w.word where length(w.word) = 1 and w.cnt >= 20 and w.cnt / u.cnt >= 0.03)", ("words", "uni_g")),
    "singles": ("singles as (select lang, word as ch, rank, cnt from lexicon where length(word) = 1)", ("lexicon",)),
    "gold": ("gold as (select sent_id, lang, w_no, word, sum(length(word)) over (partition by sent_id order by w_no) - length(word) as a, sum(length(word)) over (partition by sent_id order by w_no) as e"
             " from (select sent_id, lang, unnest(range(0, len(u))) as w_no, unnest(u) as word from (select sent_id, lang, regexp_extract_all(raw, '" + TOKEN + "') as u from test)))", ("test",)),
    "inside": ("inside as (select distinct lang, substr(word, i, 1) as a, substr(word, i + 1, 1) as b from (select lang, word, unnest(range(1, length(word))) as i from words))", ("words",)),
    "top_inside": ("top_inside as (select distinct lang, substr(word, i, 1) as a, substr(word, i + 1, 1) as b from (select lang, word, unnest(range(1, length(word))) as i from lexicon"
                   " where rank < (select greatest(2, floor(max(rank) * 25000 / 56064)) from lexicon)))", ("lexicon",)),
    "bwin": (_windows("bwin", "bench"), ("bench",)), "bedges": (_edges("bedges", "bwin", "bi", "tri"), ("bwin", "bi", "tri")), "bskips": (_skips("bskips", "bwin", "tri"), ("bwin", "tri")),
    "pbands": ("pbands as (select p.sent_id, length(p.s)::bigint as n, list(e.w order by e.i) as adj, coalesce(any_value(k.sk), []) as skip from part_names p join pedges e using (sent_id)"
               " left join (select sent_id, list(w order by i) as sk from pskips group by sent_id) k using (sent_id) group by p.sent_id, p.s)", ("pedges", "pskips")),
}


def sql(body: str, *names: str, recursive: bool = False) -> str:
    """``body`` with the expressions it names and all that they need."""
    order: list[str] = []

    def add(name: str) -> None:
        for need in CTE[name][1]:
            add(need)
        if name not in order:
            order.append(name)

    for name in names:
        add(name)
    head = ",\n".join(CTE[n][0] + "" if not n.startswith("_") else "" for n in order)
    return f"with {'recursive ' if recursive else ''}{head}{',' if body.lstrip().startswith('+') else ''}\n{body.lstrip().removeprefix('+')}"
