"""DataFrame operators: facts, representatives, rule matching, materialisation, answering, measures."""
