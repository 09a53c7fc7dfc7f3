"""Methods on facts, schema graphs, similarities, topics and relations."""
