"""Compositions of operators: the cascade, its variants, plan inspection."""
