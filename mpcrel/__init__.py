"""Select-join-aggregate queries over relations of three mutually distrusting owners, at cost linear in input and output."""
