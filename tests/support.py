"""Tables the tests read."""

SF_SMOKE = "/root/testdata/sf0.001"
SF = "/root/testdata/sf0.01"
