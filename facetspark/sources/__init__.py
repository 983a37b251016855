"""Tables and the query logs, knowledge bases and corpora derived from them."""
