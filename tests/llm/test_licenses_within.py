import re

import pytest

from regionfilter.llm import licenses

PASSAGE = " ".join(f"word{i} and license{i} of something" for i in range(200)) + "."


@pytest.mark.parametrize("name", list(licenses.TEXTS))
@pytest.mark.parametrize("glue", ["\n\n", "\n", " "])
def test_a_license_between_two_long_passages(name, glue):
    body = licenses.TEXTS[name]
    if glue == "\n\n":
        body = re.sub(r"(?<=[.]) (?=[A-Z])", "\n\n", body)
    hits = licenses.Templates().scan(f"{PASSAGE}{glue}{body}{glue}{PASSAGE}")
    assert max((h[0], h[1]) for h in hits) == (1.0, name)


def test_a_notice_in_mid_line():
    hits = licenses.Templates().scan(f"{PASSAGE} Licensed under the MIT License. {PASSAGE}")
    assert [(h[0], h[1]) for h in hits] == [(1.0, "MIT")]
    assert not licenses.Templates().scan(f"{PASSAGE} Licensed under the GNU General Public License, version 1. {PASSAGE}")
