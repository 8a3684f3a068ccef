"""Selection, representation, clustering, matching, routing and measures; all are DataFrame to DataFrame."""
