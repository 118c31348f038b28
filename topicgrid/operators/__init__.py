"""From documents or facts to a workload matrix; lengths, ranks, orders, cuts and costs."""
