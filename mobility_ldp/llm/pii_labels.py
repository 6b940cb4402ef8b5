"""The small labelled table for personal data.

Each line is a text whose personal data stands in double brackets with its
kind before a bar. All of it is invented: example domains, 555 numbers,
documentation addresses and test card numbers; none of it is from the given tables. <w> stands for any word.
"""

LINES = """
<w> <w> [[email|anna.meyer@mail.example.com]] <w> <w>
<w> [[email|j.doe+news@example.org]], <w>
<w> <w> [[email|k17 at example dot com]] <w>
<w> <w> [[email|<w> at example dot com]] <w> <w>
<w> [[email|<w> at <w> dot org]] <w>
<w> [[email|<w>.<w> at <w> dot net]], <w>
<w> <w> [[email|<w>7 at mail dot <w> dot com]]
<w>: [[email|info (at) example (dot) net]] <w>
write [[email|<w> at <w> dot com]] <w> <w>
<w> <w> [[email|<w> at <w> dot com]] please <w>
<w> <w> <w> [[email|<w> at <w> dot net]]. <w>
mail to [[email|<w>.<w> at <w> dot org]] <w> <w>
<w> <w> [[email|<w>9 at <w> dot <w> dot net]] <w>
<w> <w> [[email|<w>.<w> (at) <w> (dot) com]]. <w> <w>
<w> <w> [[email|sales [at] example [dot] org]].
<w> [[email|<w>_<w> [at] <w> [dot] com]] <w> <w>
<w> [[email|first.last at mail dot example dot com]] <w> <w>
<w> <w> [[ip|192.0.2.17]] <w>
<w> [[ip|198.51.100.3]], [[ip|203.0.113.250]] <w>
<w> [[ip|10.0.0.1]] [[email|ab.03@mail.example.com]] <w>
<w> ip [[ip|192 0 2 17]] <w>
<w> <w> address [[ip|198 . 51 . 100 . 3]] <w>
<w> server [[ip|203[.]0[.]113[.]250]] <w>
<w> <w> [[card|4111111111111111]] <w>
<w> [[card|5500 0000 0000 0004]] <w> <w>
<w> [[card|4012-8888-8888-1881]].
<w> card [[card|3782 822463 10005]] <w>
<w> card [[card|4111.1111.1111.1111]] <w>
<w> <w> card: [[card|5500/0000/0000/0004]] <w>
<w> <w> [[phone|+1 (212) 555-0147]] <w>
<w> [[phone|+44 20 7946 0958]] <w> <w>
<w> <w> [[phone|(212) 555-0147]] <w>
<w> [[phone|(415) 555-2671]], <w>
<w> <w> [[phone|415-555-2671]] <w>
<w> [[phone|646.555.0199]] <w> <w>
<w> <w> [[phone|1-800-555-0123]] <w>
<w> call [[phone|555-0182]] <w> <w>
<w> [[phone|001 212 555 0147]] <w>
<w>: [[phone|(030) 555 0134]] <w>
<w> phone [[phone|06 12 34 56 78]] <w> <w>
<w> tel [[phone|030 5550134]], <w>
<w> [[email|<w>.12@mail.example.com]] [[phone|+1 (303) 555-0100]] <w> [[card|4916338506082832]] <w>
<w> 17 <w> 2021 <w> 3.5 <w>
<w> <w> 12,000 <w> 8:30 <w> <w>
<w> 1999-2004 <w> <w>
<w> 2021-03-14 <w> 14/03/2021 <w>
<w> 14.03.2021 <w> 3. 4. 1998 <w>
<w> <w> 1.2.3 <w> 4.10 <w>
<w> (12) <w> [3] <w> <w>
<w> 100 200 300 <w> <w>
<w> 50 000 000 <w> <w>
<w> 1 2 3 4 5 6 7 <w>
<w> <w> 12 34 <w> 56 <w> 78
<w> 0.25 0.50 0.75 1.00 <w>
<w> 3.14159 <w> 2.718 <w> <w>
<w> 1,234,567.89 <w> 40% <w>
<w> token = "48160bb3fce0c31ad44167de7d05e47a1227f75a" <w>
<w> key: 9f86d081884c7d659a2feaa0c55ad015 <w>
<w> password=f37ce52754da2d09bf <w> <w>
<w> <w>_<w>_<w> = <w>7 <w>
<w> 0x7fff5fbff8c0 <w> 1e10 <w> a1b2c3
<w> <w> at <w> dot <w> <w>
<w> at <w>. <w> dot <w>
<w> <w> (at) <w> <w>
<w> <w> at <w> <w> <w>
<w> <w> [at] <w>. <w>
<w> at example <w> dot com <w>
<w> the dot <w> at the <w>
<w> + <w> - <w> ( <w> ) <w>
<w> <w>, <w> <w>. <w> <w> | <w> *** %%% ###
<w>*** <w>%%% <w>### <w> <w>&&& <w>, <w>.
<w> <w>### <w>*** <w>$$$ <w>.%%% <w> <w>&&& <w>
<w> | <w> | <w> | <w> | <w> | <w> |
| <w> <w> | <w>. <w> | <w> 17 | <w> | <w> - <w> |
<w>, <w>. <w> | <w> | <w>.<w> | <w> | <w>, | <w>
<w> - <w> - <w> - <w>; <w> / <w> / <w> / <w>
<w>: <w> (<w> <w>) <w> [<w> <w> <w>] <w>: <w>
<w> at at at at at at <w> <w> dot dot dot dot dot <w>
<w> com com com org org <w> net net <w>
<w> so so so so so so so so so so so so so so so so so so so so so so so so so so <w>
on on on on on on on on yellow yellow yellow yellow yellow yellow yellow yellow yellow yellow
<w> by by by by by by by by by upstairs upstairs upstairs upstairs upstairs upstairs upstairs <w>
a a a a a a a a a a a a a a a a a a a a a a a a a a a a a a <w>
<w> tree tree tree tree tree tree tree tree tree tree river river river river river river river.
Good good good good good good good good good good good good good good good good good good good
<w> "7A9E233A8ECF7C5B09FE5949719B6B82BC439E9329" <w>
<w> B82BC439E9329B <w> 4F5A6677C <w> 9e8d7f6a5b4c <w>
<w>!!! <w>??? <w>... <w> --- <w>___<w> ~~~ <w>
<w>, <w> *** <w> the $$$ at *** <w>%%% dot ### <w>
<w> {<w>} [<w>] (<w>) <<w>> "<w>" '<w>' <w>
<w>@ <w> @<w> # <w> $ <w> & <w> @ <w>
<w>.<w> <w>.<w>.<w> <w>-<w> <w>_<w>
<w>/<w>/825?page=2 <w> #17 <w>
http://<w>.example.com/<w>/17 <w> www.<w>.org <w>
<w> ISBN 978-3-16-148410-0 <w> <w>
<w> 3 x 4 = 12 <w> 10-20 <w>
<w> page 12 of 300 <w> section 4.2.1 <w>
<w> pages 101-117, <w> vol. 12 (3) <w>
<w> 2020 - 2024 <w> 1 + 1 <w>
<w> 12345678 <w> 987654321 <w>
<w> 1234567890123456789012 <w> <w>
<w> order 20210314-0017 <w> no. 4711 <w>
<w> version 10.4.2 <w> <w> 7% <w>
<w> 10:15:30 <w> 23:59 <w> 7 am <w>
Licensed under the Apache License, Version 2.0.
Licensed under CC BY-NC 4.0.
All rights reserved. Copyright 2019 <w> <w>.
<w> <w> <w> <w> <w> <w> <w> <w> <w> <w>.
<w> <w>, <w> <w> <w>: <w> <w> <w>; <w> <w>!
<w>
<w> <w>
""".strip().splitlines()

#: Words put in for <w>: common words of English, German, French and Spanish.
WORDS = "and then over house reading river tree the of in a for with green walk night story I x at dot Haus Wald das für und mit lesen Stadt grün schön mein bitte la maison le forêt lire avec pour été ville la ciudad niño con para leer verde noche río example com write please call number market paper road number window table Water Morning Licht Abend soir matin día".split()
KINDS = ("email", "ip", "card", "phone")


def labelled(copies: int = 10, seed: int = 7) -> list[tuple[str, list[tuple[int, int, str]]]]:
    """(text, spans): each line several times, with other words and other digits."""
    import random
    import re

    draw, out = random.Random(seed), []
    for line in LINES:
        for _ in range(copies):
            line_now = re.sub("<w>", lambda _: draw.choice(WORDS), line)
            text, spans = "", []
            for part in re.split(r"(\[\[\w+\|.*?\]\](?!\]))", line_now):
                if m := re.fullmatch(r"\[\[(\w+)\|(.*)\]\]", part):
                    inner = m[2] if m[1] in ("ip", "card") else re.sub(r"\d", lambda _: str(draw.randrange(10)), m[2])
                    spans.append((len(text), len(text) + len(inner), m[1]))
                    text += inner
                else:
                    text += part
            out.append((text, spans))
    return out
