"""Suffix arrays by linear grouping.

The Lyndon prefix of suffix i is the text from i up to p(i), the first later place whose suffix is smaller than suffix i. Suffixes
with the same Lyndon prefix form a group, and groups in the order of their prefixes are in the order of their suffixes.
Groups are found from the greatest down: at first they are the suffixes of one symbol. When a group comes up, its members are final; each
member's previous smaller place (the nearest earlier place not in a group already done, followed by pointers) has its
prefix extended by the member's, so such places leave their group for a greater one beside it, those extended by more members in a row
further up. Then the groups are gone through upwards: the places whose prefix ends before suffix i, which are its previous
smaller places, follow in their groups in the order in which i comes up, which settles each group without ranks being assigned anew.
"""

from __future__ import annotations

from collections.abc import Sequence


def suffix_array(text: Sequence[int]) -> list[int]:
    """Starts of the suffixes of text in ascending order; a suffix that is a prefix of another comes first."""
    n = len(text)
    if n < 2:
        return list(range(n))
    # A sentinel below all symbols ends the text; it is place n and the least group by itself.
    order = sorted(range(n), key=text.__getitem__)
    sa = [n, *order]
    begin = [0] * (n + 1)  # of a place's group: where the group begins in sa, which also names it
    size = {0: 1}
    at = 1
    while at <= n:
        end, symbol = at, text[sa[at]]
        while end <= n and text[sa[end]] == symbol:
            begin[sa[end]] = at
            end += 1
        size[at] = end - at
        at = end
    place = [0] * (n + 1)
    for i, s in enumerate(sa):
        place[s] = i
    previous = [-1] * (n + 1)  # previous smaller place, known once the place's group is done
    skip = list(range(-1, n))  # where to look next for it: a pointer past places that are done
    done = bytearray(n + 1)
    width = [1] * (n + 1)  # length of the Lyndon prefix known so far

    top = n
    while top > 0:
        head = begin[sa[top]]
        members = sa[head : top + 1]
        length = width[members[0]]
        for s in members:
            done[s] = 1
        # previous smaller place of each member; members that follow each other directly count together
        count: dict[int, int] = {}
        for s in members:
            p = skip[s]
            trail = [s]
            while p >= 0 and done[p]:
                trail.append(p)
                p = skip[p]
            for x in trail:
                skip[x] = p
            previous[s] = p
            if p >= 0:
                count[p] = count.get(p, 0) + 1
        if count:
            # Only a place whose known prefix ends where the member begins is extended; runs extend it once a member.
            levels: dict[int, list[int]] = {}
            for p, times in count.items():
                levels.setdefault(times, []).append(p)
            for times in sorted(levels, reverse=True):
                by_group: dict[int, list[int]] = {}
                for p in levels[times]:
                    by_group.setdefault(begin[p], []).append(p)
                    width[p] += times * length
                for g, moved in by_group.items():
                    rest = size[g] - len(moved)
                    new = g + rest
                    if rest:
                        size[g] = rest
                    else:
                        new = g
                    size[new] = len(moved)
                    # the moved places take the end of their group
                    to = new
                    gone = set(moved)
                    free = [x for x in range(new, new + len(moved)) if sa[x] not in gone]
                    stay = [p for p in moved if place[p] < new]
                    for x, p in zip(free, stay, strict=True):
                        other = sa[x]
                        back = place[p]
                        sa[back], place[other] = other, back
                        sa[x], place[p] = p, x
                    for x in range(to, to + len(moved)):
                        begin[sa[x]] = new
        top = head - 1

    # Upwards: each group's places are put in order by when the suffix behind their prefix comes up.
    fill = dict.fromkeys(set(begin), 0)
    out = [0] * (n + 1)
    out[0] = n
    fill[0] = 1
    settled = bytearray(n + 1)
    settled[n] = 1
    for i in range(n + 1):
        s = out[i] - 1
        while s >= 0:
            if not settled[s]:
                g = begin[s]
                out[g + fill[g]] = s
                fill[g] += 1
                settled[s] = 1
            else:
                break
            s = previous[s]
    return out[1:]


def common_prefixes(text: Sequence[int], sa: Sequence[int]) -> list[int]:
    """Common prefix of each suffix in sa with the one before it (0 for the first), in time linear in the text."""
    n = len(sa)
    rank, out, k = [0] * n, [0] * n, 0
    for i, s in enumerate(sa):
        rank[s] = i
    for s in range(n):
        r = rank[s]
        if r:
            o = sa[r - 1]
            top = n - max(s, o)
            while k < top and text[s + k] == text[o + k]:
                k += 1
            out[r] = k
            k = k - 1 if k else 0
        else:
            k = 0
    return out
