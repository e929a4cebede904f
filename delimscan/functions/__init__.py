"""Automata, symbol matching and packed arrays: the functions the methods are built from."""
