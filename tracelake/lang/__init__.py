"""The investigation language: text to checked statements and back."""

from tracelake.lang.analyze import analyze
from tracelake.lang.parser import LangError, parse
from tracelake.lang.tree import text_of

__all__ = ["LangError", "analyze", "parse", "text_of"]
