"""The nine activity classes of tokens, as one CASE chain and as a table that fills as tokens come."""

from __future__ import annotations

import unicodedata

#: Function words of the four languages.
FUNCTION_WORDS = (
    "the of and to in is on for with as by at an be was from that this it are or "
    "der die das und den von zu mit sich des auf ist im dem nicht ein eine "
    "le la les de et en un une du que qui dans pour au par sur pas est avec "
    "el y los del se las con para su al es como"
).split()


def class_sql(token: str, duck: bool = False) -> str:
    """The class 1..9 of a token expression; the first test that holds decides."""
    like = (lambda p: f"regexp_matches({token}, '{p}')") if duck else (lambda p: f"{token} rlike r'{p}'")
    words = ", ".join(f"'{w}'" for w in FUNCTION_WORDS)
    return (
        f"case when not {like('[0-9]|\\p{L}')} then 9 when {like('[0-9]')} then 4 when {like('[@/_]')} then 8"
        f" when lower({token}) in ({words}) then 3 when {like('^\\p{Lu}')} then 5 when {like('[^\\x00-\\x7F]')} then 6"
        f" when length({token}) <= 3 then 7 when length({token}) >= 8 then 1 else 2 end"
    )


_FUNCTION_WORDS = frozenset(FUNCTION_WORDS)
_DIGITS, _MARKS = frozenset("0123456789"), frozenset("@/_")
#: Tokens that the table holds at most before it starts anew.
HELD = 1 << 18


class TokenClasses(dict):
    """Class by token, as class_sql has it; each token is tested once."""

    def __missing__(self, token: str) -> int:
        if len(self) >= HELD:
            self.clear()
        self[token] = found = self.test(token)
        return found

    @staticmethod
    def test(token: str) -> int:
        digit = not _DIGITS.isdisjoint(token)
        if not digit and not any(unicodedata.category(c)[0] == "L" for c in token):
            return 9
        if digit:
            return 4
        if not _MARKS.isdisjoint(token):
            return 8
        if token.lower() in _FUNCTION_WORDS:
            return 3
        if unicodedata.category(token[0]) == "Lu":
            return 5
        if not token.isascii():
            return 6
        return 7 if len(token) <= 3 else 1 if len(token) >= 8 else 2
