"""Questions with their gold queries on the given tables, in SQL that Spark and DuckDB share."""

from __future__ import annotations

#: (identifier, question, gold query, difficulty)
GOLD = [
    ("Q01", "How many orders are there?", "select count(*) as n from orders", "easy"),
    ("Q02", "How many orders have status F?", "select count(*) as n from orders where o_orderstatus = 'F'", "easy"),
    ("Q03", "List the names of all regions.", "select r_name from region", "easy"),
    ("Q04", "Which market segments exist?", "select distinct c_mktsegment from customer", "easy"),
    ("Q05", "How many customers are in each market segment?", "select c_mktsegment, count(*) as n from customer group by c_mktsegment", "medium"),
    ("Q06", "How many nations belong to each region, by region name?", "select r_name, count(*) as n from region join nation on r_regionkey = n_regionkey group by r_name", "hard"),
    ("Q07", "Which order priorities have more than 3000 orders?", "select o_orderpriority from orders group by o_orderpriority having count(*) > 3000", "hard"),
    ("Q08", "Names of customers with a negative balance.", "select c_name from customer where c_acctbal < 0", "easy"),
    ("Q09", "Names of suppliers whose balance is between 1000 and 2000.", "select s_name from supplier where s_acctbal between 1000 and 2000", "easy"),
    ("Q10", "What is the largest order price?", "select max(o_totalprice) as v from orders", "easy"),
    ("Q11", "What is the smallest retail price per part type?", "select p_type, min(p_retailprice) as v from part group by p_type", "medium"),
    ("Q12", "How many different brands are there?", "select count(distinct p_brand) as n from part", "easy"),
    ("Q13", "Total quantity per return flag.", "select l_returnflag, sum(cast(l_quantity as decimal(18,2))) as q from lineitem group by l_returnflag", "medium"),
    ("Q14", "The five most expensive orders.", "select o_orderkey from orders order by o_totalprice desc, o_orderkey limit 5", "hard"),
    ("Q15", "The three smallest part keys of size 50.", "select p_partkey from part where p_size = 50 order by p_partkey limit 3", "hard"),
    ("Q16", "Customers without any order.", "select c_custkey from customer where not exists (select 1 from orders where o_custkey = c_custkey)", "hard"),
    ("Q17", "Orders without any line.", "select o_orderkey from orders where o_orderkey not in (select l_orderkey from lineitem)", "hard"),
    ("Q18", "Names of nations that have a supplier.", "select n_name from nation where n_nationkey in (select s_nationkey from supplier)", "hard"),
    ("Q19", "Nations with customers but without suppliers.", "select c_nationkey from customer except select s_nationkey from supplier", "hard"),
    ("Q20", "Nations with both customers and suppliers.", "select c_nationkey from customer intersect select s_nationkey from supplier", "hard"),
    ("Q21", "All balances above 9900 of customers or suppliers.", "select c_acctbal as v from customer where c_acctbal > 9900 union all select s_acctbal as v from supplier where s_acctbal > 9900", "hard"),
    ("Q22", "Number of orders per customer nation name.", "select n_name, count(*) as n from orders join customer on o_custkey = c_custkey join nation on c_nationkey = n_nationkey group by n_name", "extra"),
    ("Q23", "Number of lines supplied per region.", "select r_name, count(*) as n from lineitem join supplier on l_suppkey = s_suppkey join nation on s_nationkey = n_nationkey join region on n_regionkey = r_regionkey group by r_name", "extra"),
    ("Q24", "How many lines were shipped in 1997?", "select count(*) as n from lineitem where l_shipdate >= timestamp '1997-01-01 00:00:00' and l_shipdate < timestamp '1998-01-01 00:00:00'", "easy"),
    ("Q25", "Orders per year.", "select year(o_orderdate) as y, count(*) as n from orders group by year(o_orderdate)", "medium"),
    ("Q26", "How many parts have a name with the word ring?", "select count(*) as n from part where p_name like '%ring%'", "medium"),
    ("Q27", "Keys of urgent orders above 490000.", "select o_orderkey from orders where o_orderpriority = '1-URGENT' and o_totalprice > 490000", "easy"),
    ("Q28", "Number of lines with a discount of at least 0.09 or quantity of one.", "select count(*) as n from lineitem where l_discount >= 0.09 or l_quantity = 1", "medium"),
    ("Q29", "Events per type.", "select event_type, count(*) as n from events group by event_type", "medium"),
    ("Q30", "How many users made a purchase?", "select count(distinct user_id) as n from events where event_type = 'purchase'", "easy"),
    ("Q31", "Users with more than 80 events.", "select user_id from events group by user_id having count(*) > 80", "hard"),
    ("Q32", "Users who signed up but never purchased.", "select user_id from events where event_type = 'signup' except select user_id from events where event_type = 'purchase'", "hard"),
    ("Q33", "Largest value per event type.", "select event_type, max(value) as v from events group by event_type", "medium"),
    ("Q34", "Orders dearer than the average order, how many?", "select count(*) as n from orders where o_totalprice > (select avg(o_totalprice) from orders)", "hard"),
    ("Q35", "Customers with at least 18 orders.", "select o_custkey from orders group by o_custkey having count(*) >= 18", "hard"),
    ("Q36", "Parts of type ECONOMY never sold by supplier 0, how many?", "select count(*) as n from part where p_type = 'ECONOMY' and p_partkey not in (select l_partkey from lineitem where l_suppkey = 0)", "hard"),
    ("Q37", "Number of distinct customers per order status.", "select o_orderstatus, count(distinct o_custkey) as n from orders group by o_orderstatus", "medium"),
    ("Q38", "Documents per language.", "select lang, count(*) as n from documents group by lang", "medium"),
    ("Q39", "How many labelled documents have good quality, per language?", "select lang, count(*) as n from documents join labels on documents.doc_id = labels.doc_id where quality = 1 group by lang", "hard"),
    ("Q40", "Conversations with a system turn, how many?", "select count(distinct conv_id) as n from conversations where role = 'system'", "easy"),
    ("Q41", "Brands having a part of size 1 and a part of size 50.", "select p_brand from part where p_size = 1 intersect select p_brand from part where p_size = 50", "hard"),
    ("Q42", "Lines per order status and return flag.", "select o_orderstatus, l_returnflag, count(*) as n from orders join lineitem on o_orderkey = l_orderkey group by o_orderstatus, l_returnflag", "hard"),
]
