"""Tables as planes, query files, generators and table formats."""
