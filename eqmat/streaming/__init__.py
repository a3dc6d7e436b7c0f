"""Adding facts to a materialisation as they come."""
