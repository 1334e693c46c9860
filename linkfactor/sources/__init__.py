"""Tables and the observation sets derived from them."""

from .tables import document_words, events_as_observations, link_observations, purchase_lists, purchases, read_table, tokens, weighted_purchases, word_observations

__all__ = ["document_words", "events_as_observations", "link_observations", "purchase_lists", "purchases", "read_table", "tokens", "weighted_purchases", "word_observations"]
