"""Op 7: one or two spelled digits, and soft hyphens."""

from hopwise.llm import pii


def test_few_spelled_digits_and_soft_hyphens():
    cases = {
        "+1 415 555 oh one 9 9": [("phone", "+1 415 555 oh one 9 9")],
        "4111 1111 1111 111 one": [("card", "4111 1111 1111 111 one")],
        "room 12, 4111 1111 1111 111 one": [("card", "4111 1111 1111 111 one")],
        "10.0.0.one": [("ip", "10.0.0.one")],
        "192.168.one.7": [("ip", "192.168.one.7")],
        "to jo­hn@exam­ple.com now": [("email", "jo­hn@exam­ple.com")],
        "4111­1111­1111­1111": [("card", "4111­1111­1111­1111")],
        "call +1 415 555 0199 one day": [("phone", "+1 415 555 0199")],
        "one 4111 1111 1111 1111": [("card", "4111 1111 1111 1111")],
        "un 10.0.0.1": [("ip", "10.0.0.1")],
        "3 or one of 10 dogs, two in 1999": [],
        "a soft­hyphen alone": [],
    }
    for text, want in cases.items():
        base, spans = pii.all_spans(text)
        assert [(k, text[s:e]) for k, s, e in spans] == want, text
        assert set(base) <= set(spans)
