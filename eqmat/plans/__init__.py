"""What is known before Spark runs: terms, rules, ontologies, cost estimates, query trees."""
