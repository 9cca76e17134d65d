"""Which licences the template table covers."""

from tilestar.llm import licenses


def test_reserved_rights_and_bodies():
    s, bodies = licenses.Scanner(), {}
    for name, text in licenses.TEMPLATES:
        bodies[name] = max(bodies.get(name, ""), text, key=len)
    assert s.scan("Some text.\nAll rights reserved.") == ("All-rights-reserved", 1.0, 1)
    for name in ("Apache-2.0", "GPL-3.0", "MPL-2.0"):
        assert len(bodies[name]) > 10_000
        assert s.scan(bodies[name])[:2] == s.scan(" ".join(bodies[name].split()))[:2] == (name, 1.0)
    for name in ("BSD-2-Clause", "BSD-3-Clause"):
        assert s.unit(licenses.bigrams(bodies[name].lower())) == (1.0, name)
