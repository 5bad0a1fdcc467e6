"""DataFrame operators: edges, forests, certificates, decisions, separators, baselines, measures."""
