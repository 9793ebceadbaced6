"""Operators for preparing language-model training text.

Nothing else in the library imports this subpackage. Every operator module holds a
general operator; ``codist.llm.catalog`` holds the thin queries registered by the entry
module.
"""
