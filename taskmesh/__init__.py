"""taskmesh: multi-task learning over many separate datasets, as Spark plans."""
