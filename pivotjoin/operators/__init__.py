"""The stages of a join: nodes, sampling, mapping, splitting, routing, verification, and the competing joins."""
