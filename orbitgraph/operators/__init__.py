"""DataFrame operators: structures, graphs, partitions, exchange, messages, Hamiltonian blocks, measures."""
