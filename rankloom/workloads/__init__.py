"""Registered queries of the rank engine, with the same results in SQL where SQL can say them."""
