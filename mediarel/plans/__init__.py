"""Media plans: nodes, rewrites, lowering and cost."""
