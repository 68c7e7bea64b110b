"""Given tables as records, gold groups, pools and votes; a votes data source."""
