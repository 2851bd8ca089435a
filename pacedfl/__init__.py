"""Communication-efficient federated averaging as Spark plans."""
